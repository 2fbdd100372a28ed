"""Queries whose work stands on the given tables: they read them in Spark's tasks, and follow them."""

import math

import pytest

from salvage import catalog

MOVED = {"cyclic_shift": "documents", "cte_recursive_lineage": "supplier", "metric_average": "lineitem"} | {f"consensus_{kind}{n}": "documents" for kind in ("forward", "shifted") for n in (1, 2, 3)}


@pytest.mark.parametrize("name", sorted(MOVED))
def test_rows_come_from_the_table(spark, tmp_path, name):
    with pytest.raises(Exception, match=MOVED[name]):
        catalog.queries()[name](spark, str(tmp_path)).collect()


def test_each_query_reads_the_documents_itself(spark, sf, tmp_path):
    """Not what another query of the session has kept of them."""
    docs, run = spark.read.parquet(f"{sf}/documents.parquet"), catalog.queries()
    docs.where("doc_id % 2 = 0").write.parquet(f"{tmp_path}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{sf}/{name}.parquet").write.parquet(f"{tmp_path}/{name}.parquet")
    rows = lambda name, place: sorted(map(tuple, run[name](spark, place).collect()))
    before = rows("rater_kappa", str(tmp_path)), rows("consensus_forward2", str(tmp_path))
    docs.write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
    for name in ("consensus_forward2", "consensus_forward3", "consensus_shifted1", "consensus_shifted2"):
        assert rows(name, str(tmp_path)) == rows(name, sf)
    assert rows("consensus_forward2", sf) != before[1]


def test_lineage_follows_the_suppliers(spark, tmp_path):
    spark.createDataFrame([(k,) for k in (0, 1, 2, 4, 17, 40)], "s_suppkey long").write.parquet(f"{tmp_path}/supplier.parquet")
    got = {tuple(r) for r in catalog.queries()["cte_recursive_lineage"](spark, str(tmp_path)).collect()}
    assert got == {(17, 0, 3)} | {(2, 0, 1)}  # 40 hangs on 10, which is no supplier


def test_encoder_where_words_cancel_out(spark, tmp_path):
    """One text whose two words share a dimension with opposite signs has no length: no number, not an error."""
    import hashlib
    import itertools
    import string

    words, found = {}, None
    for w in map("".join, itertools.product(string.ascii_lowercase, repeat=3)):
        h = hashlib.md5(w.encode()).hexdigest()
        dim, positive = h[:2], int(h[2], 16) < 8
        if (dim, not positive) in words:
            found = words[dim, not positive], w
            break
        words[dim, positive] = w
    docs = [(1, " ".join(found)), (2, "abc")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["item_id"]: r["x"] for r in catalog.queries()["encode_sql"](spark, str(tmp_path)).collect()}
    assert math.isnan(got[1]) and abs(got[2]) == 1.0
