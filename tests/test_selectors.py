from salvage import catalog
from salvage.plans import queries_selection


def test_overlap_of_three_runs_no_other_selector(spark, sf, monkeypatch):
    def all_of_them(*_):
        raise AssertionError("all selectors are run")

    monkeypatch.setattr(queries_selection, "selections", all_of_them)
    got = {(r["a"], r["b"]): r["common"] for r in catalog.queries()["sel_overlap"](spark, sf).collect()}
    assert set(got) == {("length", "random"), ("length", "top_rated"), ("random", "top_rated")} and all(n >= 0 for n in got.values())
