"""Language identification by Bayesian fusion of evidence.

The posterior of a language for a row is proportional to
  prior by host, smoothed towards the prior by address suffix, smoothed towards the overall prior,
  times the likelihood of the text under the language's byte-trigram model (raised to a power below one, since
  neighbouring trigrams overlap),
  times the likelihood of the language that the markup declares.
The priors come from one grouped aggregation of the text-only decisions over all rows; a row's own decision is taken out
of its host's counts, so it is not evidence for itself. Rows whose evidence names no language (no letters and no
declaration, or a posterior below a half) are undetermined.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.llm.common import blocks, checkpoint, short_batches

#: Labelled rows a language that fit the text models; buckets of hashed trigrams; power of the text likelihood; chance
#: that a declaration is true; pseudo-counts of the suffix's and the overall prior; rows of the prior table that may be
#: broadcast; languages whose counts a task holds before it hands them on.
SAMPLE_ROWS, BUCKETS, TEMPER, TRUST, SMOOTH, BROADCAST_ROWS, HELD = 500, 1 << 15, 0.3, 0.9, 20.0, 20_000, 64
UNDETERMINED = "und"
_TAG = re.compile(r"<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>", re.S | re.I)


def grams(text: str | None, markup: bool = False) -> np.ndarray:
    """Buckets of the byte trigrams of the letters of a text, words set apart by one blank."""
    if markup and text:
        text = _TAG.sub(" ", text)
    b = np.frombuffer((" " + (text or "").lower() + " ").encode("utf-8", "surrogatepass"), np.uint8)
    letter = (b >= 97) & (b <= 122) | (b >= 128)
    keep = letter | np.append(True, letter[:-1])  # a letter, or the first byte after one
    b = np.where(letter, b, 32)[keep].astype(np.uint32)
    if len(b) < 4 and not letter.any():
        return np.empty(0, np.int64)
    v = (b[:-2] << 16 | b[1:-1] << 8 | b[2:]) * np.uint32(0x9E3779B1)
    return (v >> np.uint32(32 - BUCKETS.bit_length() + 1)).astype(np.int64)


class TextModel:
    """Add-half byte-trigram likelihoods, as logarithms, and the languages in order."""

    def __init__(self, languages: list[str], counts: np.ndarray):
        self.languages = languages
        counts = counts + 0.5
        self.log = np.ascontiguousarray(np.log(counts / counts.sum(1, keepdims=True)).T.astype(np.float32))

    def score(self, text: str | None, markup: bool = False) -> tuple[int, list[float]]:
        """Number of trigrams and the log-likelihood by language, relative to the best."""
        g = grams(text, markup)
        if not len(g):
            return 0, [0.0] * len(self.languages)
        total = np.zeros(len(self.languages))
        for a in range(0, len(g), 1 << 18):
            total += self.log[g[a : a + (1 << 18)]].sum(0, dtype=np.float64)
        return len(g), (total - total.max()).tolist()


def fit(docs: DataFrame, lang_col: str = "lang", id_col: str = "doc_id", text_col: str = "text", rows_per_language: int = SAMPLE_ROWS) -> TextModel:
    """Text models of every labelled language, each from at most ``rows_per_language`` of its rows.

    The rows with the least id hashes are taken; rows with a null label or a null text add nothing. Only trigram counts
    (languages x BUCKETS numbers at most) are collected; a model takes 128 KB a language.
    """
    spark = docs.sparkSession
    sizes = docs.where(F.col(lang_col).isNotNull()).groupBy(F.col(lang_col).alias("lang")).count()
    languages = sorted(r["lang"] for r in sizes.select("lang").collect())  # one row a language
    if not languages:
        return TextModel([], np.zeros((0, BUCKETS)))
    number = {name: i for i, name in enumerate(languages)}
    order = F.xxhash64("id", F.lit(11))
    share = F.least(F.lit(1.0), 3 * rows_per_language / F.col("count") + 0.01)  # about three times what is wanted goes to the exact cut
    few = docs.select(F.col(lang_col).alias("lang"), F.col(id_col).alias("id")).join(F.broadcast(sizes), "lang").where(F.pmod(order, F.lit(1 << 20)) < share * (1 << 20))
    nth = F.row_number().over(Window.partitionBy("lang").orderBy(order, "id"))
    chosen = few.withColumn("n", nth).where(F.col("n") <= rows_per_language)
    pairs = [(r["lang"], r["id"]) for r in chosen.select("lang", "id").distinct().collect()]  # at most languages x rows_per_language
    picks = F.broadcast(spark.createDataFrame(pairs, f"pick_lang string, pick {docs.schema[id_col].dataType.simpleString()}"))
    own = docs.select(F.col(id_col).alias("id"), F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("text"))
    picked = own.join(picks, F.col("id").eqNullSafe(F.col("pick")) & (F.col("lang") == F.col("pick_lang")), "left_semi")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}

        def flush() -> pa.RecordBatch:
            parts = [(i, np.flatnonzero(c), c[c > 0]) for i, c in total.items()]
            total.clear()
            columns = [np.concatenate([np.full(len(b), i) for i, b, _ in parts] or [[]]), np.concatenate([b for _, b, _ in parts] or [[]]), np.concatenate([c for _, _, c in parts] or [[]])]
            return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], ["l", "b", "n"])

        for batch in blocks(batches):
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist(), strict=True):
                found = np.bincount(grams(text), minlength=BUCKETS)
                total[number[lang]] = total.get(number[lang], 0) + found
                if len(total) > HELD:
                    yield flush()
        yield flush()

    counts = np.zeros((len(languages), BUCKETS))
    for r in short_batches(picked.select("lang", "text")).mapInArrow(count, "l bigint, b bigint, n bigint").groupBy("l", "b").agg(F.sum("n").alias("n")).collect():
        counts[r["l"], r["b"]] = r["n"]
    return TextModel(languages, counts)


def declared_in(html: Column) -> Column:
    """The primary language that a page's root element declares."""
    return F.nullif(F.lower(F.regexp_extract(html, r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-z]{2,3})\b", 1)), F.lit(""))


def host_in(url: Column) -> Column:
    return F.nullif(F.lower(F.regexp_extract(url, r"(?s)://(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))


def suffix_of(host: Column) -> Column:
    """The last label of a host name, or null for a bare name."""
    return F.nullif(F.regexp_extract(host, r"\.([^.]+)$", 1), F.lit(""))


def _salts(votes: DataFrame, parts: int):
    """Functions from host and text to a salt, and from host to its number of salts: one for each partition's worth of
    rows. Fewer than ``parts`` hosts can have more than one, and those are constants of the plan."""
    total = votes.agg(F.coalesce(F.sum("count"), F.lit(0)).alias("n")).first()["n"]
    worth = max(1, total // parts)
    hot = votes.where("_host is not null").groupBy("_host").agg(F.sum("count").alias("n")).where(F.col("n") > worth).collect()
    known = F.create_map(*(F.lit(x) for r in hot for x in (r["_host"], int(-(-r["n"] // worth)))))
    number = lambda host: F.coalesce(F.element_at(known, host), F.lit(1)) if hot else F.lit(1)
    return (lambda host, text: F.pmod(F.xxhash64(text), number(host)).cast("int")), number


def identify(df: DataFrame, model: TextModel, text: str, host: str | None = None, suffix: str | None = None, declared: str | None = None, markup: bool = False, drop_text: bool = False, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with ``language``, ``confidence`` and ``text_language``; the arguments name its columns of evidence.

    Null or empty evidence is no evidence. Columns of ``df`` with these three names are replaced. Rows are never dropped;
    repeated rows are judged alike; equal posteriors go to the first language in order; long texts are read whole; an
    empty table gives an empty result. The text is scored twice, once for the priors and once for the result, so that it
    is not moved: the table of priors is broadcast if it has few rows. Beyond that it is joined over an exchange, with
    the rows of each host that has more than its share dealt to several salts.
    """
    names = [c for c in df.columns if c not in ("language", "confidence", "text_language")]
    languages, n = model.languages, len(model.languages)
    if not n:
        return df.select(*(f"`{c}`" for c in names), F.lit(UNDETERMINED).alias("language"), F.lit(0.0).alias("confidence"), F.lit(None).cast("string").alias("text_language"))
    shared = df.sparkSession.sparkContext.broadcast(model)

    def vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in blocks(batches):
            got = [own.score(t, markup) for t in batch.column(0).to_pylist()]
            best = [g[1].index(0.0) if g[0] else None for g in got]
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array(best, pa.int32())], ["_host", "_suffix", "_best"])

    column = lambda c: F.col(f"`{c}`") if c else F.lit(None)
    evidence = df.select(column(text).alias("_text"), column(host).cast("string").alias("_host"), column(suffix).cast("string").alias("_suffix"))
    votes = checkpoint(short_batches(evidence).mapInArrow(vote, "_host string, _suffix string, _best int").where("_best is not null").groupBy("_host", "_suffix", "_best").count())  # one row a host, suffix and language
    overall = np.ones(n)
    for r in votes.groupBy("_best").agg(F.sum("count").alias("c")).collect():
        overall[r["_best"]] += r["c"]
    overall = overall / overall.sum()
    counts = F.array(*(F.sum(F.when(F.col("_best") == i, F.col("count")).otherwise(0)).cast("double") for i in range(n)))
    by_suffix = votes.where("_suffix is not null").groupBy("_suffix").agg(counts.alias("_sc"))
    by_host = votes.where("_host is not null").groupBy("_host", "_suffix").agg(counts.alias("_hc"))
    table = by_host.join(by_suffix, "_suffix", "left").select(F.col("_host").alias("_h"), F.col("_suffix").alias("_s"), "_hc", "_sc")
    salt = salted = None
    if table.count() <= broadcast_rows:
        table = F.broadcast(table)
    else:
        salt, salted = _salts(votes, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
        table = table.withColumn("_t", F.explode(F.sequence(F.lit(0), salted(F.col("_h")) - 1)))
    full = df.select(*(f"`{c}`" for c in names), column(host).cast("string").alias("_host"), column(suffix).cast("string").alias("_suffix"), F.lower(column(declared).cast("string")).alias("_declared"))
    same = (F.col("_host") == F.col("_h")) & F.col("_suffix").eqNullSafe(F.col("_s"))
    if salt is not None:
        full = full.withColumn("_salt", salt(F.col("_host"), F.col(f"`{text}`")))
        same = same & (F.col("_salt") == F.col("_t"))
    joined = full.join(table, same, "left").select(*(f"`{c}`" for c in names), "_declared", "_hc", "_sc")
    where = names.index(text)
    kept = [i for i, c in enumerate(names) if not (drop_text and c == text)]

    def decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in blocks(batches):
            out: list[tuple[str, float, str | None]] = []
            for t, said, hc, sc in zip(*(batch.column(i).to_pylist() for i in (where, len(names), len(names) + 1, len(names) + 2)), strict=True):
                out.append(posterior(own, t, markup, said, hc, sc, overall))
            arrays = [pa.array([o[0] for o in out], pa.string()), pa.array([o[1] for o in out], pa.float64()), pa.array([o[2] for o in out], pa.string())]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), *arrays], [*(names[i] for i in kept), "language", "confidence", "text_language"])

    fields = ", ".join(f"`{names[i]}` {df.schema[names[i]].dataType.simpleString()}" for i in kept)
    return short_batches(joined).mapInArrow(decide, fields + ", language string, confidence double, text_language string")


def posterior(model: TextModel, text: str | None, markup: bool, said: str | None, by_host: list[float] | None, by_suffix: list[float] | None, overall: np.ndarray) -> tuple[str, float, str | None]:
    """Language, its posterior, and the text's own choice; the row's own vote is taken out of the counts."""
    grams_, ll = model.score(text, markup)
    best = ll.index(0.0) if grams_ else None
    prior = overall
    for counts in (by_suffix, by_host):
        if counts is not None:
            c = np.array(counts)
            if best is not None:
                c[best] = max(c[best] - 1, 0)
            prior = (c + SMOOTH * prior) / (c.sum() + SMOOTH)
    log = np.log(prior) + TEMPER * np.array(ll)
    known = said in model.languages
    if known:
        log += np.where(np.array(model.languages) == said, math.log(TRUST), math.log((1 - TRUST) / max(1, len(ll) - 1)))
    odds = np.exp(log - log.max())
    i = int(odds.argmax())
    sure = round(float(odds[i] / odds.sum()), 9)
    return model.languages[i] if (grams_ or known) and sure >= 0.5 else UNDETERMINED, sure, None if best is None else model.languages[best]


def identify_corpus(docs: DataFrame, pages: DataFrame) -> DataFrame:
    """Languages of all documents and all pages, with text models learned from labelled documents.

    A page has a declared language, a host and its suffix; a document has its source in place of a host. ``kept`` says
    whether a language was found.
    """
    model = fit(docs)
    from_docs = identify(docs.select("doc_id", "text", "source"), model, "text", "source", drop_text=True)
    own = pages.select("page_id", "html", declared_in(F.col("html")).alias("declared"), host_in(F.col("url")).alias("host")).withColumn("suffix", suffix_of(F.col("host")))
    from_pages = identify(own, model, "html", "host", "suffix", "declared", True, True)
    null = lambda kind: F.lit(None).cast(kind)
    judged = lambda df, *first: df.select(*first, "language", "confidence", "text_language", (F.col("language") != UNDETERMINED).alias("kept"))
    return judged(from_docs, F.lit("documents").alias("origin"), "doc_id", null("bigint").alias("page_id"), F.col("source").alias("host"), null("string").alias("suffix"), null("string").alias("declared")).union(
        judged(from_pages, F.lit("pages").alias("origin"), null("bigint").alias("doc_id"), "page_id", "host", "suffix", "declared")
    )


def documents_in_a_language(docs: DataFrame) -> DataFrame:
    """The documents whose language was found, with the columns and values of ``docs``, whatever their names."""
    own = docs.withColumnsRenamed({c: f"d_{c}" for c in docs.columns})
    found = identify(own, fit(docs), "d_text", "d_source")
    return found.where(F.col("language") != UNDETERMINED).select(*(F.col(f"`d_{c}`").alias(c) for c in docs.columns))
