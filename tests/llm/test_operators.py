"""Each operator against brute force, and on nulls, empty and long texts, ties, repeats, empty tables and odd columns."""

import hashlib
import random
import re
import zlib
from itertools import combinations

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from salvage.llm import language_id, license_scan, mixing, packing, sharding, simhash, syncmers, toxicity, url_filter, vector_search

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "the long text goes on and on " * 4000


@pytest.fixture(scope="module")
def odd(spark):
    """Documents with nulls in every column, repeats, ties, empty and long texts."""
    rows = [
        (1, "Hello there, this is a small text about nothing.", "en", "a", 5), (1, "Hello there, this is a small text about nothing.", "en", "a", 5), (2, None, "en", None, None), (3, "", None, "a", 0),
        (4, LONG, "en", "b", len(LONG)), (None, "no id at all here", "en", "b", 3), (None, "no id at all here", "en", "b", 3), (5, "   \n\t ", "en", None, 6), (6, "Été à la plage, où il fait très chaud aujourd'hui", "fr", "c", 9), (7, "same", "en", "c", 4), (8, "same", "en", "c", 4), (9, "x", "en", "a", 1),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


# 1: exact top-k


def brute_top(rows, queries, k):
    out = []
    for qi, q in queries:
        scored = sorted((-sum(a * b for a, b in zip(q, v)), i) for i, v in rows if i != qi and len(v) == len(q))
        out += [(qi, r + 1, i, -s) for r, (s, i) in enumerate(scored[:k])]
    return sorted(out)


@pytest.mark.parametrize("spread,shard", [(3, 16), (64, 64), (64, 1000), (10**6, 50), (10**8, 40)])
def test_top_k_is_exact(spark, spread, shard):
    rng = random.Random(spread)
    rows = [(i, [rng.randint(-spread, spread) for _ in range(5)]) for i in range(300)] + [(300 + i, [1, 2, 3, 4, 5]) for i in range(40)]
    rows += [(400, [1, 2]), (401, [3, 4])]
    queries = [r for r in rows if r[0] % 7 == 0 or r[0] >= 400]
    schema = "vec_id long, v array<long>, tree string"
    frame = lambda x: spark.createDataFrame([(i, v, "clash") for i, v in x] + [(None, [1] * 5, "clash"), (999, None, "clash")], schema)
    found = vector_search.top_k(frame(rows), frame(queries), 6, shard_rows=shard, block_queries=20)
    assert sorted(map(tuple, found.collect())) == brute_top(rows, queries, 6)


def test_top_k_of_nothing(spark):
    empty = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert vector_search.embedding_neighbours(empty).count() == 0
    bad = spark.createDataFrame([(0, [1.0, None]), (20, [float("nan"), 1.0]), (40, None), (60, [0.5, 0.25]), (3, [1.0, 1.0]), (3, [1.0, 1.0])], "vec_id long, embedding array<float>")
    assert sorted(map(tuple, vector_search.embedding_neighbours(bad).collect())) == [(60, 1, 3, 3072), (60, 2, 3, 3072)]


def test_huge_components_saturate(spark):
    rows = [(0, [1e9, 1.0]), (1, [1e30, 1.0]), (2, [-1e30, 0.5]), (3, [1e9, -1.0]), (20, [1e30, 1e30]), (4, [0.0, 0.0])]
    low, high = -(2**63), 2**63 - 1
    whole = {i: [max(low, min(high, int(np.floor(64 * x)))) for x in v] for i, v in rows}
    expected = []
    for q in (0, 20):
        scored = sorted((-max(low, min(high, sum(a * b for a, b in zip(whole[q], whole[i])))), i) for i in whole if i != q)
        expected += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored)]
    got = vector_search.embedding_neighbours(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    assert sorted((r["query_id"], r["score"]) for r in got.collect()) == sorted((q, s) for q, _, _, s in expected)


def test_thresholds_travel_through_many_shards(spark):
    rng = np.random.default_rng(7)
    rows = [(i, rng.integers(-64, 65, 6).tolist()) for i in range(700)]
    frame = spark.createDataFrame(rows, "vec_id long, v array<long>")
    found = vector_search.top_k(frame, frame.where("vec_id % 9 = 0"), 4, shard_rows=40, block_queries=10)
    assert sorted(map(tuple, found.collect())) == brute_top(rows, [r for r in rows if r[0] % 9 == 0], 4)


def test_tree_boxes_are_tight_and_bound_scores():
    rng = np.random.default_rng(1)
    points = rng.integers(-64, 64, (2000, 8))
    tree = vector_search.Tree(np.arange(2000), points)
    q = rng.integers(-64, 64, (10, 8))
    for node, (a, b) in enumerate(tree.spans):
        own = tree.points[a:b]
        assert (own.min(0) == tree.low[node]).all() and (own.max(0) == tree.high[node]).all()
        assert ((q @ own.T).max(1) <= tree.bounds(q, np.array([node]))[:, 0]).all()


# 2: toxicity


@pytest.fixture(scope="module")
def toxic(spark):
    rng = random.Random(3)
    words = [f"{a}{b}" for a in "ba ce di fo gu la me ni".split() for b in "ra se ti vo lu".split()]
    rows, labels = [], []
    for i in range(900):
        text = [rng.choice(words) for _ in range(rng.randint(20, 90))]
        if i % 4 == 0:
            for _ in range(3):
                text.insert(rng.randrange(len(text)), rng.choice(["nastybad", "nastyworse", "horrid"]))
        rows.append((i, " ".join(text), "en", "a", 1))
        labels.append((i, 1, int(i % 4 == 0)))
    rows += [(1000, None, "en", "a", 1), (1001, "", "en", "a", 1), (None, "nastybad horrid thing", "en", "a", 1), (1002, "nastyevil nastyevil", "en", "a", 1)]
    return spark.createDataFrame(rows, DOCS), spark.createDataFrame(labels + [(5000, 1, 1), (1, 1, None)], "doc_id long, quality int, toxic int")


def test_toxicity_on_held_out_rows(toxic):
    found = {r["doc_id"]: r for r in toxicity.toxicity_digest(*toxic).collect()}
    assert len(found) == toxic[0].count()
    held = [r for i, r in found.items() if i is not None and i < 900 and r["held_out"]]
    assert held and all(r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in found.items() if i is not None)
    assert np.mean([r["predicted"] == (r["doc_id"] % 4 == 0) for r in held]) > 0.97
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in found.values())
    assert found[1000]["score"] == found[1001]["score"] and found[None]["held_out"] is False


def test_labels_of_the_held_out_fold_do_not_count(spark, toxic):
    flipped = toxic[1].withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    same = lambda labels: sorted(map(tuple, toxicity.toxicity_digest(toxic[0], labels).select("doc_id", "score").where("doc_id is not null").collect()))
    assert same(toxic[1]) == same(flipped)


def test_toxicity_without_labels_or_rows(spark, toxic, none):
    bare = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r["predicted"] for r in toxicity.toxicity_digest(toxic[0], bare).collect()} == {0}
    assert toxicity.toxicity_digest(none, toxic[1]).count() == 0
    kept = toxicity.drop_toxic(toxic[0], toxic[1])
    assert kept.columns == toxic[0].columns and kept.where("text like '%horrid%nastybad%'").count() == 0


def test_likelihoods_by_brute_force(toxic):
    """The chain of distributions, worked out again with dictionaries from the texts."""
    docs, labels = toxic
    model = toxicity.fit(docs, labels)
    words = {r["doc_id"]: toxicity.words_of(r["text"]) for r in docs.collect()}
    picked, _ = toxicity.training_ids(labels)
    pair = [{}, {}]
    for text, y in {tuple(words[i]): y for i, y, curve in picked if not curve and i in words}.items():
        for key in set(zip((b"", *text), text)):
            pair[y][key] = pair[y].get(key, 0) + 1
    left = [{w: len({v for v, x in p if x == w}) for w in {x for _, x in p}} for p in pair]
    known = sorted(w for w in set(left[0]) | set(left[1]) if left[0].get(w, 0) + left[1].get(w, 0) >= toxicity.WORD_COUNT)
    stem = [{s: sum(n for w, n in x.items() if toxicity.stem_of(w) == s) for s in map(toxicity.stem_of, x)} for x in left]
    stems = sorted(s for s in set(stem[0]) | set(stem[1]) if stem[0].get(s, 0) + stem[1].get(s, 0) >= toxicity.WORD_COUNT)
    unit = lambda w: ("w", w) if w in known else ("s", toxicity.stem_of(w)) if toxicity.stem_of(w) in stems else ("0", b"")
    before = {}
    for text in words.values():
        for a, b in zip(text, text[1:]):
            before.setdefault(unit(b), set()).add(unit(a))
    n_left = lambda u: len(before.get(u, ())) + 1
    units = [("0", b"")] + [("w", w) for w in known] + [("s", s) for s in stems]
    home = lambda u: u if u[0] != "w" else ("s", toxicity.stem_of(u[1])) if toxicity.stem_of(u[1]) in stems else None
    group = {u: sum(n_left(x) for x in units if home(x) == u) for u in units if u[0] != "w"}
    prob = []
    for y in (0, 1):
        total = sum(left[y].values())
        counts = {("s", s): stem[y].get(s, 0) for s in stems}
        counts["0", b""] = total - sum(counts.values())
        keep = {u: max(n - 0.75, 0) / total for u, n in counts.items()}
        by_stem = {u: keep[u] + (1 - sum(keep.values())) * group[u] / sum(group.values()) for u in counts}
        keep = {("w", w): max(left[y].get(w, 0) - 0.75, 0) / total for w in known}
        prob.append({u: keep.get(u, 0) + (1 - sum(keep.values())) * by_stem[home(u)] * n_left(u) / group[home(u)] for u in units})
    number = {u: i for i, u in enumerate(units)}
    got, rest, counted = model.distributions
    for y in (0, 1):
        assert sum(prob[y].values()) == pytest.approx(1) and got[y].sum() == pytest.approx(1)
        assert all(got[y][number[u]] == pytest.approx(x) for u, x in prob[y].items())
    told = {k for k in set(pair[0]) | set(pair[1]) if pair[0].get(k, 0) + pair[1].get(k, 0) >= toxicity.PAIR_COUNT and k[1] in known}
    size, seen = model.units.size, 0
    for v in known:
        kept = [{w: max(pair[y].get((x, w), 0) - 0.75, 0) for x, w in told if x == v} for y in (0, 1)]
        if min(sum(k.values()) for k in kept) >= toxicity.LEFT_COUNT:
            n = [sum(c for (x, _), c in pair[y].items() if x == v) for y in (0, 1)]
            share = 1 - sum(sum(k.values()) for k in kept) / sum(n)
            assert rest[number["w", v]] == pytest.approx(share)
            own = model.pairs // size == number["w", v]
            for y in (0, 1):
                want = {number["w", w]: (1 - share) * k / sum(kept[y].values()) + share * prob[y]["w", w] for w, k in kept[y].items()}
                assert dict(zip((model.pairs[own] % size).tolist(), counted[y][own].tolist())) == pytest.approx(want)
                assert sum(want.values()) + share * (1 - sum(prob[y]["w", w] for w in kept[y])) == pytest.approx(1)
            seen += 1
    assert seen > 5
    text = b" ".join(known[:30]).decode()
    ids = [number["w", w] for w in known[:30]]
    ratio = [np.log(got[1][i] / got[0][i]) for i in ids]
    at = {k: i for i, k in enumerate(model.pairs.tolist())}
    for j in range(1, 30):
        if (i := at.get(ids[j - 1] * size + ids[j])) is not None:
            ratio[j] = np.log(counted[1][i] / counted[0][i])
    assert model.features(text)[:2] == (30, pytest.approx(np.mean(ratio)))


def test_texts_labelled_both_ways_are_toxic(spark, toxic):
    docs = toxic[0].union(spark.createDataFrame([(2000 + i, "nastybad same text", "en", "a", 1) for i in range(12)], DOCS))
    labels = toxic[1].union(spark.createDataFrame([(2000 + i, 1, i % 2) for i in range(12)], toxic[1].schema))
    runs = [sorted((str(r["doc_id"]), r["score"]) for r in toxicity.toxicity_digest(docs.repartition(n), labels.repartition(n)).collect()) for n in (2, 5)]
    assert runs[0] == runs[1]


def test_continuation_counts_are_exact(spark, odd):
    units = toxicity.Units([b"hello", b"on", b"the", b"and", b"long"], [b"small", b"nothi"])
    seen = set()
    for r in odd.collect():
        ids = units.of(toxicity.words_of(r["text"])).tolist()
        seen |= set(zip(ids, ids[1:]))
    brute = [len({a for a, b in seen if b == u}) for u in range(units.size)]
    assert toxicity.continuation_counts(odd, units).tolist() == brute


def test_gaps_round_trip():
    for keys in ([0, 1, 5], [65535, 65536, 131070, 131071, 5_000_000], [7], [0, 65534, 131069]):
        assert toxicity._unpack(toxicity._pack(np.array(keys, np.int64))).tolist() == keys


# 3: licences


def brute_license(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    places = []
    for phrase, label in (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved")):
        p = phrase.split()
        places += [(i, label) for i in range(len(words)) if words[i : i + len(p)] == p]
    return len(words), sorted(places)


def test_license_counts(spark, docs, odd):
    extra = spark.createDataFrame([(90, "CC-BY, cc by cc by. General  PUBLIC\nlicense! All rights reserved", "en", "a", 1), (91, "éCC by; ccby", "en", "a", 1)], DOCS)
    table = docs.union(odd).union(extra)
    expected = []
    for r in table.collect():
        n, places = brute_license(r["text"])
        expected.append(str((r["doc_id"], n, len(places), places[0][0] if places else None, places[-1][0] if places else None, ",".join(sorted({p[1] for p in places})))))
    found = license_scan.license_digest(table).collect()
    assert sorted(expected) == sorted(str((r["doc_id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"])) for r in found)
    for r in found:
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1


def test_license_suppression_by_containment():
    names = lambda t: [d[0] for d in license_scan.detect(license_scan.words_of(t))]
    assert len(license_scan.signatures()) > 300
    assert names("GNU General Public License version 3 or any later version") == ["gpl-3.0-or-later"]
    assert names("licensed under the Apache License, Version 2.0") == ["licensed-under", "apache-2.0"] or "apache-2.0" in names("licensed under the Apache License, Version 2.0")
    assert names("CC BY-SA 4.0") == ["cc-by-sa-4.0"] and names("mit") == [] and names("") == []
    for rule in license_scan.signatures():
        assert rule.keyword


def brute_detect(text):
    words = license_scan.words_of(text)
    hits = []
    for rule in license_scan.signatures():
        pattern = re.compile(rb"(?<= )(?:" + rule.pattern.encode() + rb")(?= )")
        for m in pattern.finditer(words):
            first = words.count(b" ", 0, m.start()) - 1
            hits.append((rule.label, first, first + 1 + m.group().count(b" "), rule.priority, rule.confidence))
    taken = []
    for h in sorted(hits, key=lambda h: (-h[3], h[1] - h[2], h[1], h[0])):
        if not any(a <= h[1] and h[2] <= b for _, a, b, _, _ in taken):
            taken.append(h)
    return sorted(taken, key=lambda h: (h[1], h[2], h[0]))


LICENCES = "This program is under the GNU General Public License version 2 or later, the Mozilla Public License, v. 2.0 and CC BY-SA 4.0. Licensed under the Apache License, Version 2.0. All rights reserved. (c) Copyright 2001 2004 by X. SPDX-License-Identifier: MIT. Permission is hereby granted, free of charge, to any person obtaining a copy. "


def test_license_detections_by_brute_force(docs):
    for text in [LICENCES, LICENCES * 7, "", None, "cc by", *[r["text"] for r in docs.collect()]]:
        assert license_scan.detect(license_scan.words_of(text)) == brute_detect(text)
    labels = {d[0] for d in license_scan.detect(license_scan.words_of(LICENCES))}
    assert {"mpl-2.0", "gpl-2.0-or-later", "apache-2.0", "cc-by-sa-4.0", "mit"} <= labels
    row = license_scan.license_digest(docs.limit(1).withColumn("text", F.lit(LICENCES))).first()
    chance = 1 - 0.9 * np.prod([1 - d[4] for d in brute_detect(LICENCES)])  # a base phrase is there
    assert row["score"] == pytest.approx(chance, abs=1e-9) and row["labels"] == ",".join(sorted(labels | {"gpl", "reserved", "cc-by"}))


def test_long_licence_texts_take_linear_time():
    import time

    text = LICENCES * (10_000_000 // len(LICENCES))
    began = time.time()
    found = license_scan.detect(license_scan.words_of(text))
    assert len(found) > 200_000 and time.time() - began < 40  # some 8 s on an idle core; squared growth would be hours


# 4: urls


def test_urls_by_hand(spark):
    urls = ["https://a.Example.ORG/es/x?q", "http://example.org/en/12", "http://example.org/en/2", "http://org", "http://x.com/fr/a#b", "http://com/de/", "http://notcom/de/", None, "no scheme", "http://big.casino.net/x", "http://EXAMPLE.org?x/es/", "a://b://c/d", "http://x.net/setup.exe", ""]
    df = spark.createDataFrame([(i, u, "clash") for i, u in enumerate(urls)] + [(0, urls[0], "clash")], "page_id long, url string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(df).collect()}
    assert got[0] == ("a.example.org", "/es/x", "example.org/es/", "block") and got[1][2:] == ("example.org/en/1", "block") and got[2][2:] == ("org/", "allow")
    assert got[3] == ("org", "", None, "allow") and got[4][2:] == ("com/fr/", "allow") and got[5][2:] == ("com/de/", "block") and got[6][2:] == (None, "allow")
    assert got[7] == got[8] == got[13] == ("", "", None, "allow") and got[9][2:] == (None, "block") and got[10][:3] == ("example.org", "", None)
    assert got[11][:2] == ("b:", "//c/d") and got[12][3] == "block"
    assert url_filter.judge_urls(df).count() == len(urls) + 1 and url_filter.judge_urls(df.limit(0)).count() == 0


def test_url_plan_has_no_python(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    plan = url_filter.judge_urls(pages.select("page_id", "url"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


def test_thousands_of_rules_by_table_and_by_join(spark):
    rng = random.Random(4)
    tokens = [f"t{i}" for i in range(4000)]
    rules = [url_filter.UrlRule(f"r{i}", "block" if i % 3 else "allow", rf"(?:^|[^a-z0-9]){a}(?:[^a-z0-9]+[a-z0-9]+)*[^a-z0-9]+{b}(?:[^a-z0-9]|$)", (a, b), rng.randint(1, 5), i % 2 == 0) for i, (a, b) in enumerate(rng.sample(tokens, 2) for _ in range(6000))]
    urls = [None, "no scheme", "http://"]
    for _ in range(600):
        a, b = rng.choice(rules).tokens if rng.random() < 0.6 else rng.sample(tokens, 2)
        urls.append(f"https://{a}.example/{rng.choice(tokens)}/{b}.html?x=1")
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string")
    expected, compiled = {}, [re.compile(r.pattern) for r in rules]
    for i, u in enumerate(urls):
        m = re.match(r"(?s)^.*?://([^/?#]*)([^?#]*)", u or "")
        address = m.group(1).lower() + m.group(2) if m else ""
        best = max(((r.rank, r.name, r.action, r.listed) for r, p in zip(rules, compiled) if p.search(address)), default=None)
        expected[i] = (best[1] if best and best[3] else None, best[2] if best else "allow", best[1] if best and not best[3] else None)
    for limit in (10_000, 100):
        got = {r["page_id"]: (r["rule"], r["verdict"], r["pattern_rule"]) for r in url_filter.judge_urls(df, rules=rules, plan_rules=limit).collect()}
        assert got == expected
    assert sum(e[0] is not None or e[2] is not None for e in expected.values()) > 100
    index = {r["token"] for r in url_filter.filed_rules(df.select(F.lower("url").alias("address")), rules)[0].collect()}
    assert index <= set(tokens)


# 5: mixing


def test_targets_are_dealt_again():
    t = mixing.source_targets([("b", 100), ("a", 100), (None, 1000), ("c", 10)])
    assert t["a"] == 200 and sum(t.values()) == pytest.approx(1.5 * 1210) and t["c"] <= 20
    assert mixing.source_targets([]) == {} and mixing.source_targets([("a", 0)]) == {"a": 0}


def test_mix_meets_targets_and_agrees(docs, odd, none):
    table = docs.union(odd)
    runs = [sorted(map(tuple, mixing.mix_digest(t).select("doc_id", "size", "source_size", "target", "taken", "source").fillna(-1).fillna("~").collect())) for t in (table, table.repartition(3))]
    assert runs[0] == runs[1] and len(runs[0]) == table.count()
    by = {}
    for _, size, source_size, target, taken, source in runs[0]:
        assert 0 <= taken <= 2 * size
        x = by.setdefault(source, [0, target, 0, source_size])
        x[0] += taken
        x[2] = max(x[2], size)
    assert all(abs(taken - target) <= biggest for taken, target, biggest, _ in by.values())
    assert mixing.mix(none).count() == 0 and mixing.mixed_documents(none).count() == 0
    tree = mixing.mix(table, block_rows=4, fan_in=2).groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("t"), F.first("target").alias("g"), F.max("size").alias("m")).collect()
    assert all(abs(r["t"] - r["g"]) <= r["m"] for r in tree)


def test_mixed_documents_are_the_copies(docs, odd):
    table = docs.union(odd)
    mixed = mixing.mixed_documents(table)
    assert mixed.columns == table.columns
    words = lambda df: df.agg(F.sum(mixing.word_count(F.col("text")))).first()[0]
    assert words(mixed) == mixing.mix_digest(table).agg(F.sum("taken")).first()[0]


def test_pivot_keeps_sum_and_expectation():
    rng = np.random.default_rng(0)
    p, size, key = rng.random(40), rng.integers(1, 50, 40), rng.integers(0, 10**9, 40)
    runs = np.array([mixing.pivot(p, size, key, s) for s in range(3000)])
    assert (((runs > 0) & (runs < 1)).sum(1) <= 1).all()
    assert np.abs(runs @ size - p @ size).max() < 1e-6 and np.abs(runs.mean(0) - p).max() < 0.05


# 6: syncmers


def brute_syncmers(text):
    b = text.encode()
    h = lambda x: int(syncmers._mix(np.array([int.from_bytes(x, "big")], np.uint64))[0])
    s = [h(b[i : i + 8]) for i in range(len(b) - 7)]
    return [i for i in range(len(b) - 15) if min(s[i : i + 9]) in (s[i], s[i + 8])]


def test_syncmers_by_brute_force_and_context(odd):
    for text in ("abcdefghijklmnopqrstuvwxyz" * 3, "çà et là, un texte plus long que seize octets", "a" * 40, "short", ""):
        assert syncmers.anchors(text)[0].tolist() == brute_syncmers(text)
    old = syncmers.CHUNK
    try:
        whole = syncmers.anchors(LONG)
        syncmers.CHUNK = 1000
        cut = syncmers.anchors(LONG)
    finally:
        syncmers.CHUNK = old
    assert (whole[0] == cut[0]).all() and (whole[1] == cut[1]).all()
    rng = random.Random(5)
    a, b, c = ("".join(rng.choice("abcdefgh ") for _ in range(300)) for _ in range(3))
    inner = lambda t, shift: {(p - shift, h) for p, h in zip(*(x.tolist() for x in syncmers.anchors(t))) if shift <= p <= shift + 300 - 16}
    assert inner(b + a + c, 300) == inner(a, 0)  # whatever stands around
    assert (0, 300) in [(p - min(x for x, _ in syncmers.match_positions(a, b + a)), 300 if q - p == 300 else 0) for p, q in syncmers.match_positions(a, b + a)]


@pytest.mark.parametrize("parts", [1, 3, 40])
def test_fingerprints_follow_the_next_document(spark, docs, odd, parts):
    table = docs.union(odd)
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    try:
        found = sorted((str(r["doc_id"]), r["edited_sha256"], r["n_chars"], r["fingerprint"], r["near_next"]) for r in syncmers.fingerprint_digest(table).collect())
        single = syncmers.fingerprint_digest(odd.where("doc_id = 4")).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    rows = [(r["doc_id"], r["text"] or "") for r in table.withColumn("h", F.xxhash64(F.coalesce("text", F.lit("")))).orderBy(F.desc_nulls_last("doc_id"), "h").collect()]
    expected = []
    for i, (doc, text) in enumerate(rows):
        following = rows[(i + 1) % len(rows)][1]
        a, b = syncmers.sketch(text), syncmers.sketch(following)
        expected.append((str(doc), hashlib.sha256(syncmers.edited(text, following).encode()).hexdigest(), len(text), a.astype(">u4").tobytes().hex(), syncmers.likeness(a, b)))
    assert found == sorted(expected)
    assert single[0]["near_next"] == 1.0


def test_documents_without_ids_are_split(spark, monkeypatch):
    monkeypatch.setattr(syncmers, "RANGE_BYTES", 500)
    rng = random.Random(6)
    texts = ["".join(rng.choice("abcdefgh ") for _ in range(60)) for _ in range(150)]
    table = spark.createDataFrame([(None if i < 100 else 7, t, "guest", 1) for i, t in enumerate(texts)], "doc_id long, text string, bucket string, guest int")
    sent = syncmers.with_successors(table, "doc_id", "text")
    assert sent.where("not guest").count() == 150 and max(r["count"] for r in sent.groupBy("bucket").count().collect()) < 75
    found = {(str(r["doc_id"]), r["edited_sha256"]) for r in syncmers.fingerprint_digest(table).collect()}
    rows = [(r["doc_id"], r["text"]) for r in table.orderBy(F.desc_nulls_last("doc_id"), F.xxhash64("text")).collect()]
    assert found == {(str(d), hashlib.sha256(syncmers.edited(t, rows[(i + 1) % 150][1]).encode()).hexdigest()) for i, (d, t) in enumerate(rows)}


def test_likeness_asks_for_matching_positions():
    rng = random.Random(8)
    text = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    a, b, c = text(1500), text(1500), text(30)
    same, moved, half = syncmers.likeness(*map(syncmers.sketch, (a, c + a))), syncmers.likeness(*map(syncmers.sketch, (a, b + a))), syncmers.likeness(*map(syncmers.sketch, (a, a[:750] + b[:750])))
    assert same > 0.85 and 0.3 < moved < 0.75 and 0.1 < half < 0.6  # all anchors, those of one of two halves
    parts = [text(400) for _ in range(8)]
    mixed = syncmers.likeness(*map(syncmers.sketch, ("".join(parts), "".join(reversed(parts)))))
    assert mixed < 0.5 < syncmers.likeness(*map(syncmers.sketch, ("".join(parts), "".join(parts) + c)))


def test_fingerprints_of_nothing(none):
    assert syncmers.fingerprint_digest(none).count() == 0


# 7: language


def test_language_of_documents_and_pages(spark, docs, odd, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    found = language_id.identify_corpus(docs, pages)
    right = found.where("origin = 'documents'").join(docs.select("doc_id", "lang"), "doc_id").agg(F.avg((F.col("lang") == F.col("language")).cast("int"))).first()[0]
    assert right > 0.97 and found.count() == docs.count() + pages.count()
    right = found.where("origin = 'pages'").agg(F.avg((F.col("declared") == F.col("language")).cast("int"))).first()[0]
    assert right > 0.97
    model = language_id.fit(docs)
    judged = language_id.identify(odd.withColumn("language", F.lit(1)), model, "text", "source")
    assert judged.count() == odd.count() and {r["language"] for r in judged.where("text is null or trim(text) = ''").collect()} == {"und"}
    assert language_id.documents_in_a_language(docs).columns == docs.columns


def test_posterior_by_brute_force(docs):
    model = language_id.fit(docs)
    overall, n = np.array([0.4, 0.3, 0.2, 0.1]), len(model.languages)
    for said, host, suffix in ((None, None, None), ("fr", [3.0, 9.0, 0.0, 1.0], None), ("xx", [0.0, 0.0, 30.0, 0.0], [5.0, 5.0, 50.0, 0.0]), ("de", None, [1.0, 0.0, 0.0, 2.0])):
        for text in [r["text"] for r in docs.limit(12).collect()] + ["", None, "12 34"]:
            g = language_id.grams(text)
            like = [sum(float(model.log[x, i]) for x in g) for i in range(n)]
            best = max(range(n), key=lambda i: like[i]) if len(g) else None
            prior = [float(x) for x in overall]
            for counts in (suffix, host):
                if counts:
                    c = [max(x - (i == best), 0) for i, x in enumerate(counts)]
                    prior = [(c[i] + 20 * prior[i]) / (sum(c) + 20) for i in range(n)]
            known = said in model.languages
            logs = [np.log(prior[i]) + 0.3 * like[i] + (0 if not known else np.log(0.9) if model.languages[i] == said else np.log(0.1 / (n - 1))) for i in range(n)]
            odds = np.exp(np.array(logs) - max(logs))
            i = int(odds.argmax())
            sure = odds[i] / odds.sum()
            got = language_id.posterior(model, text, False, said, host, suffix, overall)
            assert got[0] == (model.languages[i] if (len(g) or known) and sure >= 0.5 else "und") and got[1] == pytest.approx(sure, abs=1e-4)


def test_every_labelled_language_has_a_model(spark):
    rng = random.Random(12)
    rows = []
    for k in range(90):
        alphabet = [chr(0x4E00 + 40 * k + i) for i in range(12)]
        rows += [(100 * k + j, " ".join("".join(rng.choices(alphabet, k=5)) for _ in range(30)), f"l{k:02}", "s", f"v{k}") for j in range(3 if k else 30)]
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, language string")
    model = language_id.fit(table)
    assert len(model.languages) == 90
    judged = language_id.identify(table.drop("language"), model, "text")
    assert judged.where("lang = language").count() > 0.98 * len(rows)
    kept = language_id.documents_in_a_language(table)
    assert kept.columns == table.columns and {r["language"] for r in kept.collect()} <= {f"v{k}" for k in range(90)}


def test_many_hosts_are_joined_with_salts(spark, docs):
    model = language_id.fit(docs)
    table = docs.withColumn("host", F.when(F.col("doc_id") % 3 == 0, "hot").otherwise(F.concat(F.lit("h"), F.col("doc_id") % 40)))
    judge = lambda rows: sorted((r["doc_id"], r["language"], r["confidence"]) for r in language_id.identify(table, model, "text", "host", broadcast_rows=rows).collect())
    assert judge(0) == judge(10**6)


def test_host_prior_decides_doubtful_rows(spark, docs):
    model = language_id.fit(docs)
    french = [r["text"] for r in docs.where("lang = 'fr'").limit(12).collect()]
    rows = [(i, t, "h.example", "example", None) for i, t in enumerate(french)] + [(50, "a", "h.example", "example", None), (51, "a", None, None, None), (52, "", "h.example", "example", "de"), (53, "1 2 3", "h.example", "example", "xx")]
    got = {r["i"]: r for r in language_id.identify(spark.createDataFrame(rows, "i int, text string, host string, suffix string, declared string"), model, "text", "host", "suffix", "declared").collect()}
    assert got[50]["language"] == "fr" and got[50]["confidence"] > got[51]["confidence"] or got[51]["language"] != "fr"
    assert got[52]["language"] in ("de", "fr") and got[53]["language"] == "und"


def test_language_without_rows_or_labels(none, odd):
    assert language_id.fit(none).languages == []
    assert language_id.documents_in_a_language(none).count() == 0
    unlabelled = odd.withColumn("lang", F.lit(None).cast("string"))
    assert {r["language"] for r in language_id.identify(unlabelled, language_id.fit(unlabelled), "text").collect()} == {"und"}


# 8: packing


def best_fill(lengths, counts, room):
    pool = [n for n in lengths for _ in range(counts[n])]
    return max((sum(c) for k in range(len(pool) + 1) for c in combinations(pool, k) if sum(c) <= room), default=0)


def test_fullest_is_optimal():
    rng = random.Random(2)
    for _ in range(200):
        counts = {rng.randint(1, 40): rng.randint(1, 3) for _ in range(4)}
        lengths, room = sorted(counts, reverse=True), rng.randint(1, 90)
        chosen = packing.fullest(lengths, counts, room)
        assert all(0 < c <= counts[n] for n, c in chosen.items())
        assert sum(n * c for n, c in chosen.items()) == best_fill(lengths, counts, room)


def test_packing_round_trip(spark, docs, odd):
    from tokenizers import Tokenizer

    table = docs.union(odd).union(spark.createDataFrame([(95, "a <|endoftext|> b", "en", "a", 1)], DOCS))
    tokenizer = Tokenizer.from_file(packing.tokenizer_path())
    expected = sorted((str(r["doc_id"]), zlib.crc32(np.array([*tokenizer.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4").tobytes())) for r in table.collect())
    pieces = packing.cut_pieces(table, keep_ids=True)
    rows = packing.pack_pieces(pieces, group_rows=64, fan_in=2).collect()
    docs_ids, sequences = {}, {}
    for r in rows:
        assert zlib.crc32(np.array(r["ids"], "<u4").tobytes()) == r["ids_crc32"] and len(r["ids"]) == r["length"]
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        docs_ids.setdefault((str(r["doc_id"]), r["doc_tokens"]), []).append((r["start"], r["ids"]))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    whole = []
    for (doc, total), parts in docs_ids.items():
        starts = sorted({s for s, _ in parts})
        copies = len(parts) // len(starts)
        ids = [i for s in starts for i in next(p for a, p in parts if a == s)]
        assert len(ids) == total and len(parts) == copies * len(starts)
        whole += [(doc, zlib.crc32(np.array(ids, "<u4").tobytes()))] * copies
    assert sorted(whole) == expected
    filled = [sum(n for _, n in p) for p in sequences.values()]
    wasted = sum(2048 - f for f in filled if f & (f - 1))
    assert wasted < 2 * 2048 + 0.01 * sum(filled)


def test_ids_are_those_of_the_json_file():
    from tokenizers import Tokenizer

    json_path = packing.tokenizer_path()
    encode, whole = packing.encoder(json_path), Tokenizer.from_file(json_path)
    rng = random.Random(11)
    alphabet = "abc XYZ012\n\t\r\u00a0éß中文🙂\u200d'’.,!?<|endoftext|>#$ \u3000\x00\x7f"
    texts = ["", " ", "  a  b   ", "a" * 5000, " " * 5000 + "x", "<|endoftext|>" * 3, "it's I'LL we've", "\u0301e\u0301", "🙂" * 300, "x\n" * 2000] + ["".join(rng.choice(alphabet) for _ in range(rng.randint(1, 200))) for _ in range(400)]
    ascii_ = [chr(i) for i in range(128)] + list(" \t\n''stremdlve")
    texts += ["".join(rng.choice(ascii_) for _ in range(rng.randint(1, 120))) for _ in range(1500)]
    for text in texts:
        assert encode(text).tolist() == whole.encode(text, add_special_tokens=False).ids, text[:80]


@pytest.mark.parametrize("length,each", [(1500, 1), (1000, 2), (1024, 2), (3, 682)])
def test_equal_lengths_never_reach_one_task(spark, length, each):
    rows = spark.range(3000).select("id", F.lit(length).cast("long").alias("length"))
    packed = packing.pack_pieces(rows, group_rows=256, fan_in=4)
    by = packed.groupBy("sequence_id").agg(F.count("*").alias("n"), F.sum("length").alias("filled")).collect()
    assert sum(r["n"] for r in by) == 3000 and max(r["n"] for r in by) <= each
    assert len(by) <= 3000 / each * 1.5 + 4
    sequence, _ = packing.pack_lengths(np.full(8192, length), 2048, hand_up=512)
    assert 0 < (sequence < 0).sum() <= 512 or length == 1024


def test_packing_nothing(none):
    assert packing.pack_documents(none).count() == 0


# 9: SimHash


def brute_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash_components(docs, odd):
    table = docs.union(odd)
    rows = [(r["doc_id"], brute_fingerprint(r["text"])) for r in table.collect()]
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, j in combinations(range(len(rows)), 2):
        if bin(rows[i][1] ^ rows[j][1]).count("1") <= 2:
            parent[find(j)] = find(i)
    least = {}
    for i, (doc, _) in enumerate(rows):
        if doc is not None:
            least[find(i)] = min(least.get(find(i), doc), doc)
    expected = sorted((str(doc), f"{fp:016x}", str(least.get(find(i)))) for i, (doc, fp) in enumerate(rows))
    assert sorted((str(r["doc_id"]), r["fingerprint"], str(r["component_id"])) for r in simhash.near_duplicate_digest(table).collect()) == expected
    kept = simhash.drop_near_duplicates(table)
    assert kept.columns == table.columns and kept.count() == len({find(i) for i in range(len(rows))})


def test_anchors_meet_within_the_threshold():
    rng = random.Random(7)
    for _ in range(300):
        a = rng.getrandbits(64)
        b = a
        for bit in rng.sample(range(64), rng.randint(0, 2)):
            b ^= 1 << bit
        row, anchor, home = simhash.visits(np.array([a, b], np.uint64))
        homes = [set(anchor[(row == i) & home].tolist()) for i in (0, 1)]
        all_ = [set(anchor[row == i].tolist()) for i in (0, 1)]
        assert len(homes[0]) == len(homes[1]) == 1 and homes[0] <= all_[1] and homes[1] <= all_[0]


def test_links_in_a_dense_group(spark):
    rng = np.random.default_rng(4)
    base = int(rng.integers(0, 2**62))
    group = {base ^ (1 << int(i)) ^ (1 << int(j)) for i, j in rng.integers(0, 60, (600, 2))} | {int(x) for x in rng.integers(0, 2**62, 300)}
    found = simhash.connect(simhash.links(spark.createDataFrame([(x,) for x in group], "fp long")))
    roots = {r["u"]: r["root"] for r in found.collect()}
    values = np.array(sorted(group), np.int64)
    i, j = np.nonzero(np.triu(np.bitwise_count(values[:, None] ^ values[None, :]) <= 2, 1))
    node, root = simhash.components(values[i], values[j])
    assert {a: b for a, b in zip(node.tolist(), root.tolist()) if a != b} == roots


def test_hot_anchors_are_split(monkeypatch):
    rng = np.random.default_rng(5)
    base = int(rng.integers(0, 2**62))
    group = np.array(sorted({base ^ (1 << int(i)) ^ (1 << int(j)) ^ (1 << int(k)) for i, j, k in rng.integers(0, 62, (900, 3))}), np.int64)
    row, anchor, home = simhash.visits(group.view(np.uint64))
    order = np.argsort(anchor, kind="stable")
    args = anchor[order], group[row][order], home[order]
    whole = [dict(zip(*(x.tolist() for x in simhash.components(*simhash._linked(*args)))))]
    for limit in (0, 50):
        monkeypatch.setattr(simhash, "SPLIT_PAIRS", limit)
        whole.append(dict(zip(*(x.tolist() for x in simhash.components(*simhash._linked(*args))))))
    assert whole[0] == whole[1] == whole[2] and len(whole[0]) > 500


def test_long_chains_connect(spark):
    chain = spark.createDataFrame([(i + 1, i) for i in range(200)] + [(500, 400)], "u long, v long")
    for one_task in (0, None):  # in rounds, and in one task
        assert {r["u"]: r["root"] for r in simhash.connect(chain, one_task).collect()} == {i: 0 for i in range(1, 201)} | {500: 400}


def test_simhash_of_nothing(none):
    assert simhash.near_duplicate_digest(none).count() == 0


def brute_alike(texts):
    sets = []
    for text in texts:
        words = (text or "").encode().lower().split()
        sets.append({b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set())
    return [(i, j) for i, j in combinations(range(len(texts)), 2) if sets[i] == sets[j] or 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])]


def test_near_copies_of_the_stage(spark, docs, odd):
    rng = random.Random(3)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    texts = []
    for _ in range(40):  # 0 to 6 replaced words of 60 to 200: Jaccard indexes on both sides of 0.8
        base = [word() for _ in range(rng.randint(60, 200))]
        for n in (0, 1, 2, 4, 6):
            copy = list(base)
            for at in rng.sample(range(len(copy)), n):
                copy[at] = word()
            texts.append(" ".join(copy))
    chain = [word() for _ in range(100)]  # each is like the next one only
    for i in range(40):
        texts.append(" ".join(chain[: 100]))
        chain = chain[5:] + [word() for _ in range(5)]
    table = spark.createDataFrame([(1000000 + i, t, "en", "a", len(t)) for i, t in enumerate(texts)], DOCS).union(docs).union(odd)
    rows = table.collect()
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    pairs = brute_alike([r["text"] for r in rows])
    for i, j in pairs:
        parent[find(j)] = find(i)
    least = {}
    for i, r in enumerate(rows):
        if r["doc_id"] is not None:
            least[find(i)] = min(least.get(find(i), r["doc_id"]), r["doc_id"])
    expected = sorted((str(r["doc_id"]), str(least.get(find(i)))) for i, r in enumerate(rows))
    found = simhash.near_duplicates(table)
    assert sorted((str(r["doc_id"]), str(r["component_id"])) for r in found.collect()) == expected
    kept = simhash.drop_near_duplicates(table, found)
    assert kept.columns == table.columns and kept.count() == len({find(i) for i in range(len(rows))}) < simhash.drop_near_duplicates(table).count()


def test_half_alike_copies_are_compared_within_groups(spark, monkeypatch):
    """Copies of one text on both sides of 0.8: few of their pairs are joined with shingles, and no link is lost, also
    where a group is dealt to tasks by pairs of blocks."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    base = [word() for _ in range(150)]
    texts = []
    for _ in range(260):
        copy = list(base)
        for at in rng.sample(range(150), rng.randint(0, 9)):
            copy[at] = word()
        texts.append(" ".join(copy))
    parent = list(range(len(texts)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, j in brute_alike(texts):
        a, b = sorted((find(i), find(j)))
        parent[b] = a
    table = spark.createDataFrame([(i, t, "en", "a", len(t)) for i, t in enumerate(texts)], DOCS)
    joined = []
    similar = simhash._similar
    monkeypatch.setattr(simhash, "_similar", lambda pairs, sets: joined.append(pairs.count()) or similar(pairs, sets))
    for rows in (1024, 60):
        monkeypatch.setattr(simhash, "GROUP_ROWS", rows)
        assert {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(table).collect()} == {i: find(i) for i in range(len(texts))}
    assert max(joined) < 10 * len(texts)


def test_wide_fingerprints_meet_at_the_least_index():
    rng = np.random.default_rng(8)
    for least, size in ((4, 5), (16, 20), (200, 250)):
        sets = [np.unique(rng.integers(0, 1 << 63, size, np.uint64)) for _ in range(300)]
        (bits, anchors), (other, others) = simhash.wide_fingerprints(sets), simhash.wide_fingerprints([np.sort(rng.permutation(s)[:least]) for s in sets])
        assert (anchors == others).any(1).all()
        differ = np.bitwise_count(bits ^ other)
        assert differ[:, : simhash.BITS // 8].sum(1).max() <= simhash.RADIUS and differ.sum(1, dtype=int).max() <= simhash.WIDE_RADIUS


def test_stages_keep_columns_of_any_name(spark, docs):
    names = ["key", "nth", "copies", "n", "i", "d", "h", "root", "score", "predicted", "language", "_n", "_key"]
    table = docs.limit(60).select("*", *(F.lit(f"own {c}").alias(c) for c in names))
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for kept in (simhash.drop_near_duplicates(table, simhash.near_duplicates(table)), mixing.mixed_documents(table), toxicity.drop_toxic(table, labels), language_id.documents_in_a_language(table)):
        rows = kept.collect()
        assert kept.columns == table.columns and rows and all(r[c] == f"own {c}" for r in rows for c in names)


def test_near_copies_of_nothing(none):
    assert simhash.drop_near_duplicates(none, simhash.near_duplicates(none)).count() == 0


# 10: sharding


@pytest.mark.parametrize("n", [1, 2, 3, 7, 64, 1000, 4097])
def test_permutation_is_a_bijection(n):
    p = sharding.Permutation(n)
    y = p.forward(np.arange(n))
    assert sorted(y.tolist()) == list(range(n)) and (p.backward(y) == np.arange(n)).all()
    assert n < 1000 or (y == np.arange(n)).mean() < 0.05


def test_shards(docs, odd, none):
    table = docs.union(odd)
    rows = sharding.document_shards(table).collect()
    again = sharding.document_shards(table.repartition(3)).collect()
    strip = lambda rs: sorted((str(r["doc_id"]), r["text_crc32"], r["row"], r["shard"], r["slot"]) for r in rs)
    assert strip(rows) == strip(again) and len(rows) == table.count()
    by = {}
    for r in rows:
        by.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in by.values()) and max(map(len, by.values())) - min(map(len, by.values())) <= 1
    expected = sorted((str(r["doc_id"]), len((r["text"] or "").encode()) + 1, zlib.crc32((r["text"] or "").encode())) for r in table.collect())
    assert sorted((str(r["doc_id"]), r["size"], r["text_crc32"]) for r in rows) == expected
    assert sharding.document_shards(none).count() == 0
