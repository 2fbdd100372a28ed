"""Tables derived from the given ones, with the SQL that derives them too."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from salvage.functions.keys import uniform_sql
from salvage.functions.materialize import spread
from salvage.functions.stages import Stages
from salvage.functions.vectors import DIMENSIONS, encode
from salvage.plans import correction, neighbors
from salvage.plans.correction import planted_matrix, simulate_rating
from salvage.plans.rating import grade, grade_sql
from salvage.registry import read

K, SEED = 6, 42
T6 = planted_matrix(K, 0.75)
P6 = np.array([0.05, 0.07, 0.04, 0.01, 0.79, 0.04])


def truth6(spark: SparkSession, sf: str) -> DataFrame:
    """(sample_id, component, n_chars, y): the rubric's grade as the true class."""
    docs = spread(read(spark, sf, "documents").select("doc_id", "source", "n_chars", "text"))
    return docs.select(F.col("doc_id").alias("sample_id"), F.col("source").alias("component"), "n_chars", grade(F.col("text")).alias("y"))


def ratings6(spark: SparkSession, sf: str, seed: int = SEED) -> DataFrame:
    """truth6 with raw_score: the true class through the planted transition matrix."""
    if seed != SEED:
        return simulate_rating(truth6(spark, sf), T6, seed=seed)
    return Stages(spark, sf).table("ratings", lambda: simulate_rating(truth6(spark, sf), T6))


def text_vectors(spark: SparkSession, sf: str, kind: str = "char3") -> DataFrame:
    """(sample_id, vec) of the documents, encoded once a session."""
    docs = spread(read(spark, sf, "documents").select("doc_id", "text"))
    return Stages(spark, sf).table(f"vectors-{kind}", lambda: encode(docs, "doc_id", "text", kind))


def text_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    """The two nearest documents of each."""
    return Stages(spark, sf).table("neighbours", lambda: neighbors.knn(text_vectors(spark, sf), 2))


def text_triples(spark: SparkSession, sf: str) -> DataFrame:
    """(sample_id, y1, y2, y3, component, y): each document's rating and those of its neighbours."""
    rated = ratings6(spark, sf)
    return correction.neighbour_scores(text_neighbours(spark, sf), rated).join(rated.select("sample_id", "component", "y"), "sample_id")


def given_vectors(spark: SparkSession, sf: str) -> DataFrame:
    """(sample_id, vec, label) of the embeddings table."""
    return read(spark, sf, "embeddings").select(F.col("vec_id").alias("sample_id"), F.col("embedding").alias("vec"), "label")


def _matrix_sql(m: np.ndarray) -> str:
    return "[" + ", ".join("[" + ", ".join(f"{float(x)!r}::DOUBLE" for x in row) + "]" for row in m) + "]"


_CUMULATIVE = np.cumsum(T6, 1)
_CUMULATIVE[:, -1] = 2.0
TRUTH_SQL = f"truth6 AS (SELECT doc_id AS sample_id, source AS component, n_chars, text, {grade_sql()} AS y FROM documents)"
RATINGS_SQL = f"""{TRUTH_SQL}, ratings6 AS (SELECT *, len(list_filter(({_matrix_sql(_CUMULATIVE)})[y + 1], lambda c: c <= {uniform_sql('sample_id', SEED)}))::INT AS raw_score FROM truth6)"""
T6_SQL, P6_SQL = _matrix_sql(T6), "[" + ", ".join(f"{float(x)!r}::DOUBLE" for x in P6) + "]"

#: Pairs of the embeddings table with a cosine of at least 0.3, and each row's neighbours by cosine.
PAIRS_SQL = "unit_ AS (SELECT vec_id AS sample_id, label, embedding::DOUBLE[] AS v FROM embeddings), sims AS (SELECT x.sample_id AS a, y.sample_id AS b, round(list_cosine_similarity(x.v, y.v), 9) AS s FROM unit_ x JOIN unit_ y ON x.sample_id <> y.sample_id), pairs AS (SELECT a, b, round(s, 6) AS sim FROM sims WHERE a < b AND round(s, 6) >= 0.3)"
NEIGHBOURS_SQL = PAIRS_SQL + ", knn AS (SELECT a AS sample_id, nn_rank, b AS nn_id, s AS sim FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS nn_rank FROM sims) WHERE nn_rank <= 2)"


def encoder_sql(name: str, source: str) -> str:
    """CTEs that end with ``name`` (id, v): the character trigram vectors of ``source`` (id, text), in SQL.

    The hash of a trigram is worked out in 128 bits modulo 2^64; a component is rounded to a float as the table's are.
    """
    wrap = "18446744073709551616::UHUGEINT"
    return f"""{name}_src AS (SELECT id, [ord(c) FOR c IN string_split(lower(text), '')] AS cs FROM ({source})),
{name}_at AS (SELECT id, cs, unnest(range(1, len(cs) - 1)) AS i FROM {name}_src WHERE len(cs) >= 3),
{name}_tf AS (SELECT id, (cs[i]::BIGINT << 42) + (cs[i + 1]::BIGINT << 21) + cs[i + 2] AS gram, count(*) AS tf FROM {name}_at GROUP BY 1, 2),
{name}_x AS (SELECT gram, ((gram::UHUGEINT * 11400714819323198485::UHUGEINT) % {wrap})::UBIGINT AS x FROM (SELECT DISTINCT gram FROM {name}_tf)),
{name}_y AS (SELECT gram, ((xor(x, x >> 29)::UHUGEINT * 13787848793156543929::UHUGEINT) % {wrap})::UBIGINT AS x FROM {name}_x),
{name}_h AS (SELECT gram, xor(x, x >> 32) AS h FROM {name}_y),
{name}_b AS (SELECT id, (h % {DIMENSIONS})::INT AS dim, sum(CASE WHEN h >= 9223372036854775808 THEN -1 ELSE 1 END * (1 + ln(tf))) AS s FROM {name}_tf JOIN {name}_h USING (gram) GROUP BY 1, 2),
{name}_n AS (SELECT id, sqrt(sum(s * s)) AS n FROM {name}_b GROUP BY 1),
{name}_g AS (SELECT id, d::INT AS dim FROM {name}_src, range({DIMENSIONS}) r(d)),
{name} AS (SELECT g.id, list(coalesce((s / nullif(n, 0))::FLOAT::DOUBLE, 0) ORDER BY g.dim) AS v FROM {name}_g g LEFT JOIN {name}_b b ON b.id = g.id AND b.dim = g.dim LEFT JOIN {name}_n n ON n.id = g.id GROUP BY 1)"""


def cosine_sql(x: str, y: str) -> str:
    """The cosine, 0 for a zero vector."""
    return f"coalesce(CASE WHEN list_sum(list_transform({x}, lambda e: abs(e))) = 0 OR list_sum(list_transform({y}, lambda e: abs(e))) = 0 THEN 0 ELSE list_cosine_similarity({x}, {y}) END, 0)"


TEXT_SQL = encoder_sql("tv", "SELECT doc_id AS id, text FROM documents")
TEXT_SIMS_SQL = f"{TEXT_SQL}, tz AS (SELECT id, v, list_sum(list_transform(v, lambda e: abs(e))) = 0 AS z FROM tv), tsims AS (SELECT x.id AS a, y.id AS b, CASE WHEN x.z OR y.z THEN 0 ELSE round(list_cosine_similarity(x.v, y.v), 9) END AS s FROM tz x JOIN tz y ON x.id <> y.id)"
TEXT_KNN_SQL = f"{TEXT_SIMS_SQL}, tknn AS (SELECT a AS sample_id, nn_rank, b AS nn_id, s AS sim FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS nn_rank FROM tsims) WHERE nn_rank <= 2)"
TRIPLES_SQL = f"{RATINGS_SQL}, {TEXT_KNN_SQL}, triples6 AS (SELECT r.sample_id, r.component, r.y, r.raw_score AS y1, max(CASE WHEN nn_rank = 1 THEN n.raw_score END) AS y2, max(CASE WHEN nn_rank = 2 THEN n.raw_score END) AS y3 FROM ratings6 r JOIN tknn k ON k.sample_id = r.sample_id JOIN ratings6 n ON n.sample_id = k.nn_id GROUP BY ALL)"


def bayes_sql(source: str, cols: list[str], name: str = "fixed", p: str = P6_SQL, t: str = T6_SQL) -> str:
    """CTEs that end with ``name``: ``source`` with post and corrected under p and T; y1 is the own rating."""
    product = " * ".join(f"({t})[i + 1][{c} + 1]" for c in cols)
    weights = f"list_transform(range({K}), lambda i: ({p})[i + 1] * {product})"
    return f"{name}_w AS (SELECT *, list_transform(w, lambda x: round(x / list_sum(w), 9)) AS post FROM (SELECT *, {weights} AS w FROM {source})), {name} AS (SELECT *, CASE WHEN post[y1 + 1] = list_max(post) THEN y1 ELSE list_position(post, list_max(post)) - 1 END::INT AS corrected FROM {name}_w)"


#: The likelihood estimate: expectation and maximisation over the counted triples, as a recursion over lists.
STEPS = 50
_R = f"range({K})"
LIKELIHOOD_SQL = f"""{TRIPLES_SQL}, cells6 AS (SELECT y1, y2, y3, count(*)::DOUBLE AS n FROM triples6 GROUP BY 1, 2, 3),
cl AS (SELECT list(cells6) AS cl FROM cells6),
own6 AS (SELECT list_transform({_R}, lambda i: coalesce(list_sum(list_transform(list_filter(cl, lambda c: c.y1 = i), lambda c: c.n)), 0) / list_sum(list_transform(cl, lambda c: c.n))) AS p FROM cl),
em(it, p, t) AS (SELECT 0, p, list_transform({_R}, lambda i: list_transform({_R}, lambda j: CASE WHEN i = j THEN 0.7::DOUBLE ELSE 0.06::DOUBLE END)) FROM own6
  UNION ALL
  SELECT it + 1, list_transform(ni, lambda x: x / list_sum(ni)),
         list_transform({_R}, lambda i: list_transform({_R}, lambda j: list_sum(list_transform(rs, lambda c: c.r[i + 1] * ((c.y1 = j)::INT + (c.y2 = j)::INT + (c.y3 = j)::INT))) / (3 * greatest(ni[i + 1], 1e-300))))
  FROM (SELECT it, rs, list_transform({_R}, lambda i: list_sum(list_transform(rs, lambda c: c.r[i + 1]))) AS ni
        FROM (SELECT it, list_transform(ws, lambda c: {{'y1': c.y1, 'y2': c.y2, 'y3': c.y3, 'r': list_transform(c.w, lambda x: c.n * x / greatest(list_sum(c.w), 1e-300))}}) AS rs
              FROM (SELECT it, list_transform(cl, lambda c: {{'y1': c.y1, 'y2': c.y2, 'y3': c.y3, 'n': c.n, 'w': list_transform({_R}, lambda i: p[i + 1] * t[i + 1][c.y1 + 1] * t[i + 1][c.y2 + 1] * t[i + 1][c.y3 + 1])}}) AS ws FROM em, cl WHERE it < {STEPS})))),
found AS (SELECT p AS fp, t AS ft FROM em WHERE it = {STEPS})"""

#: The low documents: ratings, text neighbours, estimated T and p, correction and cut. Needs WITH RECURSIVE.
SCORED_SQL = f"{LIKELIHOOD_SQL}, sourced AS (SELECT * FROM triples6, found), {bayes_sql('sourced', ['y1', 'y2', 'y3'], 'fixed', 'fp', 'ft')}"
LOW_SQL = f"{SCORED_SQL}, low AS (SELECT f.sample_id, f.component, f.y, f.y1 AS raw_score, f.corrected, t.text, t.n_chars FROM fixed f JOIN truth6 t USING (sample_id) WHERE corrected <= 2)"
