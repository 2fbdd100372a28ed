"""Toxicity by class-conditional Kneser-Ney models.

Two bigram models over words, one of toxic and one of ordinary texts, are learned from a bounded sample of labelled rows,
with up to RATIO times as many rows of the commoner class. Each is an absolute-discount chain: bigram, then word, then
the stem class of the word (its first letters, for rare forms of an expression), then continuation counts that both
classes share. What a level discounts, or leaves out for being too rare, goes to the level below it, so that each
distribution adds up to 1. How much a left word leaves to the level below is estimated from both classes together, so
that a word that was merely not seen after it says nothing by that; a left word conditions what follows once both
classes have seen it, and before that both back off. The shared counts are the numbers of distinct left units of a unit
over all texts, labelled or not; left words that the sample does not know count by their stem. Of a word that is not in
the sample only the stem counts as evidence, not how large the sample of a class was. A text's evidence is the difference of the two log-likelihoods per word, over the whole text
and over its most toxic expressions; a logistic curve fitted on sampled rows that the counts left out turns it into a
score. Bigrams count the texts that hold them; words and stems count their distinct left neighbours, so that neither a
text that repeats itself nor a group of copies passes for support.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import blocks, checkpoint, short_batches

#: Labelled rows a class that fit the model; how many times larger one class's sample may be; letters of a stem; least
#: sample counts of a word and of a bigram with its own parameters; least discounted count, in each class, of a left word
#: that conditions what follows; expressions in the peak; discount; keys kept before a task hands on what it has.
SAMPLE_ROWS, RATIO, STEM, WORD_COUNT, PAIR_COUNT, LEFT_COUNT, PEAK, DISCOUNT, FLUSH = 4000, 9, 5, 2, 3, 5, 3, 0.75, 1 << 20
#: Weights of the curve (constant, ratio per word, expressions of the peak) where there is nothing to fit them on.
PLAIN = (-3.0, 1.0) + (1 / PEAK,) * PEAK
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()


def stem_of(word: bytes) -> bytes:
    """The first letters of a word, whole code points."""
    return word[:STEM] if word.isascii() else word.decode("utf-8", "replace")[:STEM].encode()


class Units:
    """Numbers for the known words, the stems of words, and 0 for the rest."""

    def __init__(self, words: list[bytes], stems: list[bytes]):
        self.word = {w: 1 + i for i, w in enumerate(words)}
        self.stem = {s: 1 + len(words) + i for i, s in enumerate(stems)}
        self.size = 1 + len(words) + len(stems)

    def of(self, words: list[bytes]) -> np.ndarray:
        word, stem = self.word.get, self.stem.get
        return np.array([word(w) or stem(stem_of(w), 0) for w in words], np.int64)


def _pack(keys: np.ndarray) -> bytes:
    """Ascending distinct keys as 16-bit gaps; 65535 stands for that gap without a key."""
    gaps = np.diff(keys, prepend=0)
    skips, rest = gaps // 65535, gaps % 65535
    out = np.full(len(keys) + int(skips.sum()), 65535, np.uint16)
    out[np.cumsum(skips + 1) - 1] = rest
    return out.tobytes()


def _unpack(packed: bytes) -> np.ndarray:
    gaps = np.frombuffer(packed, np.uint16)
    return np.cumsum(gaps.astype(np.int64))[gaps != 65535]


def continuation_counts(docs: DataFrame, units: Units, text_col: str = "text") -> np.ndarray:
    """The number of distinct left neighbours of each unit over all texts.

    A task sends its distinct (left, right) keys in ranges, coded as gaps; ranges follow the number of tasks, so that
    what a reducer reads stays the same as the input grows. One number a unit reaches the driver.
    """
    size, spark = units.size, docs.sparkSession
    ranges = max(64, 4 * docs.select(text_col).rdd.getNumPartitions())
    span = -(-size * size // ranges)
    shared = spark.sparkContext.broadcast(units)

    def collect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, held, n = shared.value, [], 0

        def flush() -> pa.RecordBatch:
            keys = np.unique(np.concatenate(held))
            cuts = np.searchsorted(keys, np.arange(ranges + 1) * span)
            parts = [(i, _pack(keys[a:b] - i * span)) for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if b > a]
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in parts], pa.int32()), pa.array([p[1] for p in parts], pa.binary())], ["range", "keys"])

        for batch in blocks(batches):
            for text in batch.column(0).to_pylist():
                ids = own.of(words_of(text))
                if len(ids) > 1:
                    held.append(np.unique(ids[1:] * size + ids[:-1]))
                    n += len(held[-1])
            if n > FLUSH:
                yield flush()
                held, n = [], 0
        if held:
            yield flush()

    def merge(rows: pa.Table) -> pa.Table:
        i, keys = rows.column("range")[0].as_py(), np.unique(np.concatenate([_unpack(k.as_py()) for k in rows.column("keys")]))
        right, count = np.unique((keys + i * span) // size, return_counts=True)
        return pa.table({"unit": pa.array(right, pa.int64()), "n": pa.array(count, pa.int64())})

    counts = np.zeros(size)
    sent = short_batches(docs.select(text_col)).mapInArrow(collect, "range int, keys binary")
    for r in sent.groupBy("range").applyInArrow(merge, "unit bigint, n bigint").groupBy("unit").agg(F.sum("n").alias("n")).collect():
        counts[r["unit"]] = r["n"]
    return counts


class Model:
    """Log-likelihood ratios (toxic over ordinary) of units and of counted bigrams, and the curve to a score."""

    def __init__(self, units: Units, unit_ratio: np.ndarray, pairs: np.ndarray, pair_ratio: np.ndarray):
        self.units, self.unit_ratio, self.pairs, self.pair_ratio = units, unit_ratio, pairs, pair_ratio
        self.weights = np.array(PLAIN)

    def features(self, text: str | None) -> tuple[int, float, list[float]]:
        """Words, the ratio per word of the whole text, and the ratios of its PEAK most toxic expressions."""
        ids = self.units.of(words_of(text))
        n = len(ids)
        if not n:
            return 0, 0.0, [0.0] * PEAK
        ratio = self.unit_ratio[ids]
        if n > 1:
            key = ids[:-1] * self.units.size + ids[1:]
            if len(self.pairs):
                at = np.minimum(np.searchsorted(self.pairs, key), len(self.pairs) - 1)
                hit = self.pairs[at] == key
                ratio[1:][hit] = self.pair_ratio[at[hit]]
        unlike = ratio[np.unique(ids, return_index=True)[1]]
        top = np.maximum(np.sort(unlike)[::-1][:PEAK], 0).tolist()
        return n, float(ratio.mean()), top + [0.0] * (PEAK - len(top))

    def score(self, n: int, mean: float, top: list[float]) -> float:
        """The chance of label 1; ``n``, the number of words, has no part in it beyond the mean."""
        z = float(np.dot(self.weights, [1.0, mean, *top]))
        return 1 / (1 + math.exp(-max(-700.0, min(700.0, z))))


def _curve(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Ridge logistic regression by Newton steps."""
    w, ridge = np.zeros(x.shape[1]), np.diag([1e-3] + [1e-2] * (x.shape[1] - 1))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + ridge, x.T @ (weight * (y - p)) - ridge @ w)
        w = w + step
        if np.abs(step).max() < 1e-8:
            break
    return w


def training_ids(labels: DataFrame, rows: int = SAMPLE_ROWS, id_col: str = "doc_id", label_col: str = "toxic") -> tuple[list[tuple], float]:
    """(id, label, for the curve) of the sample, at most ``rows`` of each class and RATIO times as many as of the other,
    and the share of toxic rows among labelled ones. An id labelled both ways is toxic. Rows whose id has crc32 of 0 modulo 5 are never used; those of 1 are kept for the curve."""
    fold = F.crc32(F.col(id_col).cast("string")) % 5
    usable = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(label_col).alias("y"), fold.alias("fold")).where("fold <> 0")
    usable = usable.groupBy("id").agg(F.max("y").alias("y"), F.first("fold").alias("fold"))
    found = {r["y"]: r["count"] for r in usable.groupBy("y").count().collect()}
    few = min(found.get(0, 0), found.get(1, 0))
    n = min(rows, RATIO * few)
    picked = [r for y in (0, 1) for r in usable.where(F.col("y") == y).orderBy(F.xxhash64("id", F.lit(5)), "id").limit(n).collect()] if n else []
    return [(r["id"], r["y"], r["fold"] == 1) for r in picked], found.get(1, 0) / max(1, sum(found.values()))


def fit(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text") -> Model | None:
    """The model, or None without labelled rows of both classes. At most ``rows`` ids a class and the counts of their
    words reach the driver; the shared counts cover all of ``docs``."""
    spark = docs.sparkSession
    picked, toxic_share = training_ids(labels, rows)
    if not picked:
        return None
    chosen = F.broadcast(spark.createDataFrame(picked, "pick bigint, y int, curve boolean"))
    sample = checkpoint(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).join(chosen, F.col("id") == F.col("pick")).groupBy("text").agg(F.max("y").alias("y"), F.max("curve").alias("curve")))  # a text labelled both ways is toxic

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally: dict[tuple[bytes, bytes], list[int]] = {}

        def flush() -> pa.RecordBatch:
            columns = [pa.array([k[i] for k in tally], pa.binary()) for i in (0, 1)]
            out = pa.RecordBatch.from_arrays([*columns, *(pa.array([n[y] for n in tally.values()], pa.int64()) for y in (0, 1))], ["v", "w", "n0", "n1"])
            tally.clear()
            return out

        for batch in blocks(batches):
            for text, y in zip(batch.column("text").to_pylist(), batch.column("y").to_pylist(), strict=True):
                words = words_of(text)
                for key in set(zip([b"", *words], words)):
                    tally.setdefault(key, [0, 0])[y] += 1
                if len(tally) > FLUSH >> 3:
                    yield flush()
        yield flush()

    both = sample.where("not curve").select("text", "y").mapInArrow(count, "v binary, w binary, n0 bigint, n1 bigint")
    both = checkpoint(both.groupBy("v", "w").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")))
    neighbours = [F.sum((F.col(f"n{y}") > 0).cast("long")).alias(f"n{y}") for y in (0, 1)]
    often = lambda least: F.col("n0") + F.col("n1") >= least
    words_of_sample = checkpoint(both.groupBy("w").agg(*neighbours))
    sums = [F.sum(f"n{y}").alias(f"n{y}") for y in (0, 1)]
    whole = words_of_sample.agg(*sums).first()
    by_word = {bytes(r["w"]): (r["n0"], r["n1"]) for r in words_of_sample.where(often(WORD_COUNT)).toLocalIterator()}
    by_stem = words_of_sample.groupBy(F.substring(F.col("w").cast("string"), 1, STEM).cast("binary").alias("w")).agg(*sums)
    stem_counts = {bytes(r["w"]): (r["n0"], r["n1"]) for r in by_stem.where(often(WORD_COUNT)).toLocalIterator()}
    units = Units(sorted(by_word), sorted(stem_counts))
    told = both.where(often(PAIR_COUNT)).join(words_of_sample.where(often(WORD_COUNT)).select("w"), "w", "left_semi")
    kept = told.groupBy("v").agg(*(F.sum(F.greatest(F.col(f"n{y}") - DISCOUNT, F.lit(0.0))).alias(f"k{y}") for y in (0, 1)))
    lefts = both.where("length(v) > 0").groupBy("v").agg(*sums).join(kept.where(F.least("k0", "k1") >= LEFT_COUNT), "v")
    left_facts = lefts.toArrow().to_pylist()
    pairs = told.join(lefts.select("v"), "v", "left_semi").toArrow()

    shared = continuation_counts(docs, units, text_col) + 1.0
    words = len(units.word)
    total = np.maximum([whole["n0"] or 0, whole["n1"] or 0], 1)
    unit_counts = np.zeros((2, units.size))
    for w, i in units.word.items():
        unit_counts[:, i] = by_word[w]
    stems = np.zeros(units.size, np.int64)
    for w, i in units.word.items():
        stems[i] = units.stem.get(stem_of(w), 0)
    stem_share = np.zeros(units.size)  # shared counts of a stem's words and of its other forms
    np.add.at(stem_share, stems[1 : 1 + words], shared[1 : 1 + words])
    stem_share[1 + words :] += shared[1 + words :]
    stem_share[0] = shared[0]
    in_all = stem_share / stem_share.sum()
    class_stem, class_unit = np.zeros((2, units.size)), np.zeros((2, units.size))
    for y in (0, 1):
        n = np.zeros(units.size)
        for s, i in units.stem.items():
            n[i] = stem_counts[s][y]
        n[0] = total[y] - n.sum()
        kept = np.maximum(n - DISCOUNT, 0) / total[y]
        class_stem[y] = kept + (1 - kept.sum()) * in_all
        kept = np.maximum(unit_counts[y] - DISCOUNT, 0) / total[y]
        own = np.zeros(units.size)
        own[1 : 1 + words] = class_stem[y][stems[1 : 1 + words]] * shared[1 : 1 + words] / np.where(stems[1 : 1 + words] > 0, stem_share[stems[1 : 1 + words]], shared[0])
        own[1 + words :] = class_stem[y][1 + words :] * shared[1 + words :] / stem_share[1 + words :]
        loose = (stems == 0) & (np.arange(units.size) > 0) & (np.arange(units.size) <= words)  # known words without a stem class
        own[0] = class_stem[y][0] - own[loose].sum()
        class_unit[y] = kept + (1 - kept.sum()) * own
    unit_ratio = np.log(class_unit[1] / class_unit[0])
    unit_ratio[1 + words :] = np.log(class_stem[1][1 + words :] / class_stem[0][1 + words :])
    unit_ratio[0] = math.log(class_stem[1][0] / class_stem[0][0])
    rest = np.ones(units.size)  # what a left word leaves, in either class, for words without a parameter of their own after it
    mass = np.ones((2, units.size))  # its discounted counts
    for r in left_facts:
        if i := units.word.get(r["v"]):
            rest[i] = 1 - (r["k0"] + r["k1"]) / (r["n0"] + r["n1"])
            mass[:, i] = r["k0"], r["k1"]
    word = units.word.get
    v, w = (np.array([word(x, 0) for x in pairs.column(c).to_pylist()], np.int64) for c in ("v", "w"))
    known = (v > 0) & (w > 0)
    v, w = v[known], w[known]
    p = [(1 - rest[v]) * np.maximum(pairs.column(f"n{y}").to_numpy()[known] - DISCOUNT, 0) / mass[y, v] + rest[v] * class_unit[y, w] for y in (0, 1)]
    keys = v * units.size + w
    order = np.argsort(keys)
    model = Model(units, unit_ratio, keys[order], np.log(p[1] / p[0])[order])
    model.distributions = class_unit, rest, [x[order] for x in p]  # for tests; some numbers a unit and a bigram

    own_model = spark.sparkContext.broadcast(model)

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            got = [own_model.value.features(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.list_(pa.float64()))], ["y", "n", "mean", "top"])

    held = sample.where("curve").select("text", "y").mapInArrow(measure, "y int, n bigint, mean double, top array<double>").orderBy("y", "n", "mean", "top").collect()
    if {r["y"] for r in held} == {0, 1}:
        x = np.array([[1.0, r["mean"], *r["top"]] for r in held])
        y = np.array([float(r["y"]) for r in held])
        weight = np.where(y == 1, toxic_share / y.mean(), (1 - toxic_share) / (1 - y.mean()))
        model.weights = _curve(x, y, weight)
    return model


def score_texts(df: DataFrame, model: Model | None, text_col: str = "text", drop_text: bool = False) -> DataFrame:
    """``df`` with n_words, llr_mean, llr_peak, score and predicted (1 from a score of a half on); columns of these names
    are replaced. A null text is an empty one, whose evidence is nil; repeated rows and equal texts have equal scores;
    long texts are read whole; an empty table gives an empty result. Without a model every score is 0."""
    added = ["n_words", "llr_mean", "llr_peak", "score", "predicted"]
    names = [c for c in df.columns if c not in added]
    where = names.index(text_col)
    kept = [i for i, c in enumerate(names) if not (drop_text and c == text_col)]
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in blocks(batches):
            got = [own.features(t) if own else (0, 0.0, [0.0] * PEAK) for t in batch.column(where).to_pylist()]
            score = [own.score(*g) if own else 0.0 for g in got]
            arrays = [pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.float64()), pa.array([sum(g[2]) / PEAK for g in got], pa.float64()), pa.array(score, pa.float64()), pa.array([int(s >= 0.5) for s in score], pa.int32())]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), *arrays], [*(names[i] for i in kept), *added])

    fields = ", ".join(f"`{names[i]}` {df.schema[names[i]].dataType.simpleString()}" for i in kept)
    return short_batches(df.select(*(f"`{c}`" for c in names))).mapInArrow(run, fields + ", n_words bigint, llr_mean double, llr_peak double, score double, predicted int")


def toxicity_digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row a document: held_out (false for a null id), score, predicted and the evidence; see score_texts."""
    scored = score_texts(docs.select("doc_id", "text"), fit(docs, labels), drop_text=True)
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", "predicted", "n_words", "llr_mean", "llr_peak")


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that are not predicted toxic, with the columns of ``docs``."""
    scored = score_texts(docs.withColumnsRenamed({c: f"d_{c}" for c in docs.columns}), fit(docs, labels), "d_text")
    return scored.where("predicted = 0").select(*(F.col(f"d_{c}").alias(c) for c in docs.columns))
