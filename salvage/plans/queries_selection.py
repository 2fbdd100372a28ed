"""Queries over the competing ways of choosing rows of the low set."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.functions.keys import order_key_sql, uniform_sql
from salvage.functions.materialize import checkpoint
from salvage.functions.together import together
from salvage.functions.vectors import encode
from salvage.plans import lm, neighbors, select
from salvage.plans.chain import Chain, low_documents
from salvage.plans.fixtures import LOW_SQL, RATINGS_SQL, SCORED_SQL, encoder_sql, text_vectors
from salvage.plans.queries_clusters import LOW_PAIRS_SQL, greedy_sql
from salvage.plans.queries_correction import RUBRIC_SQL
from salvage.plans.rating import rubric
from salvage.plans.samples import samples_from_documents
from salvage.registry import query, read

_LOW = f"{LOW_SQL}, budget AS (SELECT floor(count(*) * {select.SHARE})::BIGINT AS n FROM low)"


def _low(spark, sf) -> DataFrame:
    return low_documents(spark, sf).withColumnRenamed("doc_id", "sample_id")


def _n(df: DataFrame) -> int:
    """The budget of every selector."""
    return int(df.count() * select.SHARE)


def _take_sql(source: str, score: str, order: str = "DESC", ctes: str = _LOW, first: str = "0") -> str:
    return f"WITH RECURSIVE {ctes}, scored AS (SELECT sample_id, ({score})::DOUBLE AS score, {first} AS f FROM {source}) SELECT sample_id, round(score, 6) AS score, rank FROM (SELECT *, row_number() OVER (ORDER BY f, score {order} NULLS LAST, {order_key_sql('sample_id')}, sample_id) AS rank FROM scored) WHERE rank <= (SELECT n FROM budget)"


for _name, _cond in (("base_low", "tier = 'low'"), ("base_high", "tier = 'high'"), ("base_full", "true")):

    def _base(spark, sf, cond=_cond):
        return Chain(spark, sf).scored().where(cond).select("sample_id", F.col("y1").alias("raw_score"), "corrected")

    query(_name, f"WITH RECURSIVE {SCORED_SQL}, s AS (SELECT sample_id, r.raw_score, corrected, CASE WHEN corrected IS NULL THEN 'unassigned' WHEN corrected <= 2 THEN 'low' ELSE 'high' END AS tier FROM ratings6 r LEFT JOIN (SELECT sample_id, corrected FROM fixed) USING (sample_id)) SELECT sample_id, raw_score, corrected FROM s WHERE {_cond}")(_base)


@query("base_prior", "SELECT quality AS predicted, count(*) AS support FROM labels GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 1")
def base_prior(spark, sf):
    """The learner without any training rows: its prior."""
    return read(spark, sf, "labels").groupBy(F.col("quality").alias("predicted")).agg(F.count("*").alias("support")).orderBy(F.desc("support"), "predicted").limit(1)


@query("sel_length", _take_sql("low", "length(text)"))
def sel_length(spark, sf):
    low = _low(spark, sf)
    return select.by_length(low, _n(low))


@query("sel_length_words", _take_sql("low", "len(regexp_extract_all(text, '[^ \\n\\t]+'))"))
def sel_length_words(spark, sf):
    low = _low(spark, sf)
    return select.by_length(low, _n(low), "words")


_FAR = "far AS (SELECT a AS sample_id, round(avg(d), 5) AS d FROM (SELECT a, d, row_number() OVER (PARTITION BY a ORDER BY d, b) AS r FROM (SELECT x.id AS a, y.id AS b, round(list_distance(x.v, y.v), 9) AS d FROM tv x JOIN tv y ON x.id <> y.id WHERE x.id IN (SELECT sample_id FROM low) AND y.id IN (SELECT sample_id FROM low))) WHERE r <= {} GROUP BY 1)"


def _low_vectors(spark, sf) -> DataFrame:
    return Chain(spark, sf).low_vectors()


for _i in (1, 5, 10):

    def _knn(spark, sf, i=_i):
        v = _low_vectors(spark, sf)
        return select.by_knn(v, _n(v), i)

    query(f"sel_knn{_i}", _take_sql("low LEFT JOIN far USING (sample_id)", "d", ctes=f"{_LOW}, {_FAR.format(_i)}"))(_knn)

_GRAMS = "w AS (SELECT sample_id AS id, regexp_extract_all(lower(text), '[a-zà-ÿ]+') AS ws FROM ratings6), g AS (SELECT id, unnest(list_concat(['<s>'], ws[1:len(ws) - 1])) AS v, unnest(ws) AS w FROM w WHERE len(ws) > 0), cvw AS (SELECT v, w, count(*) AS c FROM g GROUP BY 1, 2), cv AS (SELECT v, sum(c) AS c FROM cvw GROUP BY 1), cw AS (SELECT w, sum(c) AS c FROM cvw GROUP BY 1), t AS (SELECT sum(c) AS n, count(*) AS types FROM cw), ppl AS (SELECT id AS sample_id, round(exp(-avg(ln(0.7 * cvw.c / cv.c + 0.25 * cw.c / t.n + 0.05 / t.types))), 6) AS ppl FROM g JOIN cvw USING (v, w) JOIN cv USING (v) JOIN cw USING (w), t GROUP BY 1)"


def _ppl(spark, sf, rows: DataFrame | None = None) -> DataFrame:
    """Perplexities of all documents, or of ``rows`` (sample_id, text) of them; the counts are of all."""
    docs = read(spark, sf, "documents").withColumnRenamed("doc_id", "sample_id")
    grams = lm.bigrams(docs, "sample_id", F.col("text"))
    own = None if rows is None else lm.bigrams(rows, "sample_id", F.col("text"))
    counts = lm.Counts(grams, None if rows is None else lm.words(docs, F.col("text")))
    return counts.perplexity(own).select(F.col("id").alias("sample_id"), F.round("ppl", 6).alias("ppl"))


@query("lm_perplexity", f"WITH {RATINGS_SQL}, {_GRAMS} SELECT sample_id, round(ppl, 3) AS ppl FROM ppl")
def lm_perplexity(spark, sf):
    return _ppl(spark, sf).select("sample_id", F.round("ppl", 3).alias("ppl"))


for _end in ("low", "high", "middle"):

    def _perplexity(spark, sf, end=_end):
        low = _low(spark, sf)
        scored = low.select("sample_id").join(_ppl(spark, sf, low), "sample_id", "left")
        return select.by_perplexity(scored, _n(low), end).select("sample_id")

    _score = "ppl" if _end != "middle" else "abs(ppl - (SELECT median(ppl) FROM lp))"
    query("sel_perplexity" if _end == "low" else f"sel_perplexity_{_end}", f"WITH RECURSIVE {_LOW}, {_GRAMS}, lp AS (SELECT low.sample_id, ppl.ppl FROM low LEFT JOIN ppl USING (sample_id)) SELECT sample_id FROM (SELECT sample_id, row_number() OVER (ORDER BY round({_score}, 6) {'DESC' if _end == 'high' else 'ASC'} NULLS LAST, {order_key_sql('sample_id')}, sample_id) AS rank FROM lp) WHERE rank <= (SELECT n FROM budget)")(_perplexity)


@query("sel_random", _take_sql("low", uniform_sql("sample_id"), "ASC"))
def sel_random(spark, sf):
    low = _low(spark, sf)
    return select.at_random(low, _n(low))


@query("sel_top_rated", _take_sql("low", "raw_score"))
def sel_top_rated(spark, sf):
    low = _low(spark, sf)
    return select.top_rated(low, _n(low))


_SPLIT = r"'(?s)^([^.!?]*[.!?])\s+(.+)$'"
#: Counts of all other responses: a row's own counts are taken out of every total.
_DIFFICULTY = f"""smp AS (SELECT sample_id AS id, regexp_extract_all(lower(regexp_extract(text, {_SPLIT}, 1)), '[a-zà-ÿ]+') AS wi, regexp_extract_all(lower(regexp_extract(text, {_SPLIT}, 2)), '[a-zà-ÿ]+') AS wr FROM low WHERE regexp_extract(text, {_SPLIT}, 2) <> ''),
g AS (SELECT id, unnest(list_concat(['<s>'], wr[1:len(wr) - 1])) AS v, unnest(wr) AS w FROM smp WHERE len(wr) > 0),
own AS (SELECT id, v, w, count(*) AS k, sum(count(*)) OVER (PARTITION BY id, w) AS kw, sum(count(*)) OVER (PARTITION BY id, v) AS kv, sum(count(*)) OVER (PARTITION BY id) AS kn FROM g GROUP BY 1, 2, 3),
cvw AS (SELECT v, w, count(*) AS c FROM g GROUP BY 1, 2), cv AS (SELECT v, sum(c) AS c FROM cvw GROUP BY 1), cw AS (SELECT w, sum(c) AS c FROM cvw GROUP BY 1), t AS (SELECT sum(c) AS n, count(*) AS types FROM cw),
ci AS (SELECT id, w, count(*) AS c FROM (SELECT id, unnest(wi) AS w FROM smp) GROUP BY 1, 2), li AS (SELECT id, sum(c) AS n FROM ci GROUP BY 1),
p AS (SELECT own.id, k, {{p}} AS p, coalesce(ci.c, 0) AS c, coalesce(li.n, 0) AS l FROM own JOIN cvw USING (v, w) JOIN cv USING (v) JOIN cw USING (w) LEFT JOIN ci ON ci.id = own.id AND ci.w = own.w LEFT JOIN li ON li.id = own.id, t),
ifd AS (SELECT id AS sample_id, round(exp(sum(k * ln(p)) / sum(k) - sum(k * ln((c + {lm.PRIOR_WORDS} * p) / (l + {lm.PRIOR_WORDS}))) / sum(k)), 6) AS difficulty FROM p GROUP BY 1)"""
_LOW_P = "0.25 * (cw.c - kw) / greatest(t.n - kn, 1) + 0.05 / t.types"
_BIG, _SMALL = f"{_LOW_P} + 0.7 * CASE WHEN cv.c - kv > 0 THEN (cvw.c - k) / (cv.c - kv) ELSE 0 END", f"({_LOW_P}) / 0.30"


def _ifd_sql(p: str) -> str:
    score = "CASE WHEN difficulty < 1 THEN difficulty ELSE -difficulty END"
    return _take_sql("low LEFT JOIN ifd USING (sample_id)", score, ctes=f"{_LOW}, {_DIFFICULTY.replace('{p}', p)}", first="coalesce((difficulty >= 1)::INT, 2)")


def difficulties(spark, sf, order: int) -> DataFrame:
    """(sample_id, difficulty) of all low documents; null for one without a response."""
    low = _low(spark, sf).withColumnRenamed("sample_id", "doc_id")
    scored = lm.difficulty(samples_from_documents(low), order).withColumnRenamed("id", "sample_id")
    return low.select(F.col("doc_id").alias("sample_id")).join(scored, "sample_id", "left")


@query("sel_ifd", _ifd_sql(_BIG))
def sel_ifd(spark, sf):
    scored = difficulties(spark, sf, 2)
    return select.by_difficulty(scored, _n(scored))


@query("sel_ifd_small", _ifd_sql(_SMALL))
def sel_ifd_small(spark, sf):
    scored = difficulties(spark, sf, 1)
    return select.by_difficulty(scored, _n(scored))


@query("ifd_rank_corr")
def ifd_rank_corr(spark, sf):
    """How far the small model ranks rows as the large one does."""
    big, small = (difficulties(spark, sf, n).where("difficulty is not null") for n in (2, 1))
    return lm.rank_correlation(big, small.withColumnRenamed("difficulty", "small"), "sample_id", "difficulty", "small")


def _diverse_sql(quality: str) -> str:
    score = f"((low.{quality} + 1) * (complexity + 1))"
    nodes = f"{LOW_PAIRS_SQL}, budget AS (SELECT floor(count(*) * {select.SHARE})::BIGINT AS n FROM low), {RUBRIC_SQL}, rated AS (SELECT low.*, complexity, {score} AS s FROM low JOIN rubric ON doc_id = sample_id)"
    return _take_sql("rated", "s", ctes=f"{nodes}, {greedy_sql('s DESC', 'rated', 'lpairs')}", first="(sample_id NOT IN (SELECT c FROM cents))::INT")


def scored_diverse(spark, sf, quality: str) -> DataFrame:
    low = _low(spark, sf)
    # Complexity is of a text alone, so no other document's words are counted.
    dims = rubric(low.select(F.col("sample_id").alias("doc_id"), "text")).select(F.col("doc_id").alias("sample_id"), "complexity")
    rows = low.select("sample_id", quality).join(dims, "sample_id")
    return select.score_diverse_of(rows, _low_vectors(spark, sf), (F.col(quality) + 1) * (F.col("complexity") + 1), _n(low))


@query("sel_score_diverse", _diverse_sql("raw_score"))
def sel_score_diverse(spark, sf):
    """Raw rating times the rubric's complexity on the low documents, greedily diverse at 0.9."""
    return scored_diverse(spark, sf, "raw_score")


@query("sel_score_diverse_corrected", _diverse_sql("corrected"))
def sel_score_diverse_corrected(spark, sf):
    """The same with the corrected rating."""
    return scored_diverse(spark, sf, "corrected")


def _targets(spark, sf, cond: str = "true") -> DataFrame:
    return encode(read(spark, sf, "benchmark").where(cond), "item_id", "text").select(F.col("sample_id").alias("target_id"), F.col("vec").alias("tvec"))


_TARGETS = encoder_sql("bv", "SELECT item_id AS id, text FROM benchmark")


@query("sel_target_sim", f"WITH RECURSIVE {_LOW}, {_TARGETS}, s AS (SELECT t.id AS t, x.id AS x, CASE WHEN list_max(x.v) = 0 AND list_min(x.v) = 0 THEN 0 ELSE round(list_cosine_similarity(t.v, x.v), 9) END AS s FROM bv t JOIN tv x ON x.id IN (SELECT sample_id FROM low)), r AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY s DESC, x) AS turn FROM s), f AS (SELECT x, min(struct_pack(turn := turn, t := t + 1)) AS m, max(s) AS s FROM r GROUP BY 1) SELECT x AS sample_id, round(s, 6) AS score, rank FROM (SELECT *, row_number() OVER (ORDER BY m, x) AS rank FROM f) WHERE rank <= (SELECT n FROM budget)")
def sel_target_sim(spark, sf):
    """Low documents in turn by their similarity to the benchmark's items."""
    v = _low_vectors(spark, sf)
    return select.by_target(v, _targets(spark, sf), _n(v))


@query("sel_target_sim_best")
def sel_target_sim_best(spark, sf):
    """The best of several target subsets: the one whose chosen low documents are most similar to their targets."""
    v = _low_vectors(spark, sf)
    n = _n(v)
    runs = together(*(lambda k=k: select.by_target(v, _targets(spark, sf, f"item_id % 3 = {k}"), n).withColumn("subset", F.lit(k)) for k in range(3)))
    means = [(k, r.agg(F.avg("score")).first()[0] or 0.0) for k, r in enumerate(runs)]  # three numbers
    return runs[max(means, key=lambda m: (m[1], -m[0]))[0]]


@query("sel_corrected_rare", _take_sql("low LEFT JOIN far USING (sample_id)", "corrected * 1000 + coalesce(d, 0)", ctes=f"{_LOW}, {_FAR.format(10)}"))
def sel_corrected_rare(spark, sf):
    """Corrected rating first, rarity among the low documents' vectors second."""
    low, v = _low(spark, sf), _low_vectors(spark, sf)
    far = neighbors.knn(v, 10, "euclid").groupBy("sample_id").agg(F.round(-F.avg("sim"), 5).alias("d"))
    return select.corrected_rare(low.select("sample_id", "corrected").join(far, "sample_id", "left").fillna(0.0, ["d"]), _n(low))


@query("sel_rules", _take_sql("low", "length(text)", first="(NOT (length(text) BETWEEN 100 AND 20000 AND len(regexp_extract_all(text, '[#*%&$!|]')) / greatest(length(text), 1) <= 0.05))::INT"))
def sel_rules(spark, sf):
    low = _low(spark, sf)
    return select.by_rules(low, _n(low))


def all_selections(spark, sf) -> dict[str, DataFrame]:
    """Every selector by the uniform interface: the same low documents, the same budget, exactly as many rows. None waits
    for another but the two that share the distances of the neighbours."""
    low, v = _low(spark, sf), _low_vectors(spark, sf)
    n, pick = _n(low), select.select

    def far_ones() -> dict[str, DataFrame]:
        far = checkpoint(select.distances(v, 10))
        rare = low.select("sample_id", "corrected").join(far, "sample_id", "left").fillna(0.0, ["d"])
        return {"knn10": pick(v, "knn", n, i=10, far=far), "corrected_rare": pick(rare, "corrected_rare", n)}

    steps = {
        "knn10 corrected_rare": far_ones, "score_diverse": lambda: scored_diverse(spark, sf, "raw_score"), "score_diverse_corrected": lambda: scored_diverse(spark, sf, "corrected"),
        "target_sim_best": lambda: sel_target_sim_best(spark, sf), "target_sim": lambda: pick(v, "target_sim", n, targets=_targets(spark, sf)),
        "perplexity": lambda: pick(low.select("sample_id").join(_ppl(spark, sf, low), "sample_id", "left"), "perplexity", n),
        "difficulty": lambda: pick(difficulties(spark, sf, 2), "difficulty", n), "difficulty_small": lambda: pick(difficulties(spark, sf, 1), "difficulty", n),
        "length": lambda: pick(low, "length", n), "random": lambda: pick(low, "random", n), "top_rated": lambda: pick(low, "top_rated", n), "rules": lambda: pick(low, "rules", n),
    }
    found: dict[str, DataFrame] = {}
    for name, chosen in zip(steps, together(*steps.values()), strict=True):
        found |= chosen if isinstance(chosen, dict) else {name: chosen}
    return {m: found[m] for m in _METHODS}


def selections(spark, sf) -> DataFrame:
    """(method, sample_id, rank) of all selectors, written once a session."""
    from salvage.functions.stages import Stages

    def build() -> DataFrame:
        out = None
        for method, chosen in all_selections(spark, sf).items():
            part = chosen.select(F.lit(method).alias("method"), "sample_id", F.col("rank").cast("bigint").alias("rank"))
            out = part if out is None else out.union(part)
        return out

    return Stages(spark, sf).table("selections", build)


_METHODS = "length knn10 perplexity random top_rated difficulty difficulty_small score_diverse score_diverse_corrected target_sim target_sim_best corrected_rare rules".split()


@query("sel_budgets", f"WITH RECURSIVE {_LOW} SELECT m.method, n, true AS of_low FROM (VALUES " + ", ".join(f"('{m}')" for m in _METHODS) + ") m(method), budget")
def sel_budgets(spark, sf):
    """Each selector returns exactly its budget, and only low documents."""
    low = _low(spark, sf).select("sample_id", F.lit(1).alias("one"))
    joined = selections(spark, sf).join(low, "sample_id", "left")
    return joined.groupBy("method").agg(F.countDistinct("sample_id").alias("n"), (F.count("*") == F.count("one")).alias("of_low"))


def _rank_sql(score: str, order: str) -> str:
    return f"SELECT sample_id FROM (SELECT sample_id, row_number() OVER (ORDER BY {score} {order}, {order_key_sql('sample_id')}, sample_id) AS r FROM low) WHERE r <= (SELECT n FROM budget)"


@query("sel_overlap", f"WITH RECURSIVE {_LOW}, s AS (SELECT 'length' AS method, sample_id FROM ({_rank_sql('length(text)', 'DESC')}) UNION ALL SELECT 'random', sample_id FROM ({_rank_sql(uniform_sql('sample_id'), 'ASC')}) UNION ALL SELECT 'top_rated', sample_id FROM ({_rank_sql('raw_score', 'DESC')})), n AS (SELECT method, count(*) AS n FROM s GROUP BY 1), c AS (SELECT x.method AS a, y.method AS b, count(*) AS common FROM s x JOIN s y USING (sample_id) GROUP BY 1, 2) SELECT a.method AS a, b.method AS b, coalesce(common, 0) AS common, round(coalesce(common, 0) / (a.n + b.n - coalesce(common, 0)), 6) AS jaccard FROM n a JOIN n b ON a.method < b.method LEFT JOIN c ON c.a = a.method AND c.b = b.method")
def sel_overlap(spark, sf):
    """Common rows of three selectors, two at a time; no other selector is run."""
    low = _low(spark, sf)
    n, out = _n(low), None
    for method in ("length", "random", "top_rated"):
        part = select.select(low, method, n).select(F.lit(method).alias("method"), "sample_id")
        out = part if out is None else out.union(part)
    return select.overlap(out)


@query("sel_overlap_all")
def sel_overlap_all(spark, sf):
    """Common rows of all selectors, two at a time."""
    return select.overlap(selections(spark, sf))
