"""The surface for Python kernels: scalar, Arrow, iterator, grouped, aggregate, table and cogrouped functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F

from salvage.functions.vectors import mean_vectors
from salvage.registry import query, read

_FIRST = "SELECT e.vec_id, round(list_dot_product(e.embedding::DOUBLE[], f.embedding::DOUBLE[]), 6) AS sim FROM embeddings e, (SELECT embedding FROM embeddings ORDER BY vec_id LIMIT 1) f"


def _with_first(spark, sf):
    e = read(spark, sf, "embeddings").select("vec_id", "embedding")
    return e.crossJoin(F.broadcast(e.orderBy("vec_id").limit(1).select(F.col("embedding").alias("other"))))


@query("udf_scalar", _FIRST)
def udf_scalar(spark, sf):
    dot = F.udf(lambda a, b: float(sum(x * y for x, y in zip(a, b))), "double")  # row by row: for reference only
    return _with_first(spark, sf).select("vec_id", F.round(dot("embedding", "other"), 6).alias("sim"))


@query("udf_arrow", _FIRST)
def udf_arrow(spark, sf):
    @F.arrow_udf("double")
    def dot(a: pa.Array, b: pa.Array) -> pa.Array:
        x, y = (np.asarray(c.flatten(), float).reshape(len(c), -1) for c in (a, b))
        return pa.array((x * y).sum(1))

    return _with_first(spark, sf).select("vec_id", F.round(dot("embedding", "other"), 6).alias("sim"))


@query("udf_iter", _FIRST)
def udf_iter(spark, sf):
    first = read(spark, sf, "embeddings").orderBy("vec_id").first()["embedding"]

    @F.pandas_udf("double")
    def dot(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        other = np.array(first, float)  # set up once for all batches
        for batch in batches:
            yield pd.Series(np.array(batch.tolist(), float) @ other)

    return read(spark, sf, "embeddings").select("vec_id", F.round(dot("embedding"), 6).alias("sim"))


@query("udf_group", "SELECT label, count(*) AS n, round(max(n_), 6) AS longest FROM (SELECT label, sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) AS n_ FROM embeddings) GROUP BY 1")
def udf_group(spark, sf):
    def run(rows: pa.Table) -> pa.Table:
        x = np.asarray(rows.column("embedding").combine_chunks().flatten(), float).reshape(rows.num_rows, -1)
        return pa.table({"label": rows.column("label").slice(0, 1), "n": pa.array([len(x)], pa.int64()), "longest": pa.array([round(float(np.linalg.norm(x, axis=1).max()), 6)])})

    return read(spark, sf, "embeddings").select("label", "embedding").groupBy("label").applyInArrow(run, "label int, n bigint, longest double")


@query("udaf_vec_mean", "SELECT label, i, round(avg(x), 6) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY 1, 2")
def udaf_vec_mean(spark, sf):
    means = mean_vectors(read(spark, sf, "embeddings"), ["label"], "embedding")
    return means.select("label", F.posexplode("mean").alias("i", "m")).select("label", F.col("i").cast("bigint").alias("i"), F.round("m", 6).alias("m"))


@query("udtf_sentences", "SELECT item_id, n, trim(s) AS sentence FROM (SELECT item_id, unnest(parts) AS s, generate_subscripts(parts, 1) - 1 AS n FROM (SELECT item_id, string_split(text, '.') AS parts FROM benchmark)) WHERE trim(s) <> ''")
def udtf_sentences(spark, sf):
    @F.udtf(returnType="n bigint, sentence string")
    class Sentences:
        def eval(self, text: str):
            for n, part in enumerate((text or "").split(".")):
                if part.strip(" "):
                    yield n, part.strip(" ")

    spark.udtf.register("salvage_sentences", Sentences)
    read(spark, sf, "benchmark").createOrReplaceTempView("salvage_items")
    return spark.sql("select item_id, s.n, s.sentence from salvage_items, lateral salvage_sentences(text) s")


@query("cogroup_pairs", "SELECT coalesce(d.doc_id, l.doc_id) % 50 AS g, count(d.doc_id) AS docs, count(l.doc_id) AS labels FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1")
def cogroup_pairs(spark, sf):
    keyed = lambda t: read(spark, sf, t).select((F.col("doc_id") % 50).alias("g"), "doc_id")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        g = (left if left.num_rows else right).column("g").slice(0, 1)
        return pa.table({"g": g, "docs": pa.array([left.num_rows]), "labels": pa.array([right.num_rows])})

    return keyed("documents").groupBy("g").cogroup(keyed("labels").groupBy("g")).applyInArrow(run, "g bigint, docs bigint, labels bigint")


@query("sql_udf", "SELECT item_id, (lower(trim(text)) = lower(text))::INT AS same FROM benchmark")
def sql_udf(spark, sf):
    spark.sql("create or replace temporary function salvage_exact(a string, b string) returns int return cast(lower(trim(a)) = lower(b) as int)")
    read(spark, sf, "benchmark").createOrReplaceTempView("salvage_items")
    return spark.sql("select item_id, salvage_exact(text, text) as same from salvage_items")
