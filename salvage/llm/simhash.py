"""SimHash near-duplicates by anchor points of a covering code.

Fingerprints of 64 bits link at two or fewer differing bits. Anchors are pairs of words of the binary Golay code, one
for bits 0-22 and one for bits 23-45. That code covers every 23-bit word within distance 3 by exactly one of its words.
So a fingerprint has one home anchor within the covering radius, and whoever links to it with d1 and d2 differing bits
in the two parts (d1 + d2 <= 2) lies within 3 + d1 and 3 + d2 of that anchor. Each fingerprint is sent to all anchors
within those distances, about 61 of 16.7 million, and only the visitors and residents of one anchor are compared.
Equal fingerprints are one node from the start, and an anchor gives a star for each component it sees, not pairs. An
anchor with very many visitors is split by further bits: two fingerprints that differ in two bits at most agree in one
of three thirds of their 64 bits, so only rows that agree in a third are compared there.

Two bits of three-word shingles are far stricter than a similarity of 0.8, so the pipeline's stage takes the same steps
with wider fingerprints (``near_duplicates``): SimHash counts of five-word shingles, anchors that are words of a code,
fingerprints compared where they meet at an anchor, and an exact check of the Jaccard index. There the counts themselves
choose the anchor, not their signs alone: at 0.8 a sixth of the signs differ, which no anchor of signs bears.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from salvage.llm.common import blocks, checkpoint, short_batches

SHINGLE, SEED, THRESHOLD = 3, 42, 2
_BITS, _RADIUS, _GENERATOR = 23, 3, 0b101011100011  # fixed values of the Golay code
#: Rows that are compared together, pairs compared at once, and pairs from which an anchor is split by further bits.
CHUNK_ROWS, CHUNK_PAIRS, SPLIT_PAIRS = 1 << 19, 1 << 21, 1 << 16
#: Links (16 bytes each) up to which one task connects them all; more are connected in rounds, with the same result.
ONE_TASK = 1 << 20
#: Near duplicates: words of a shingle and the least Jaccard index (4 of 5).
WORDS, LEAST = 5, (4, 5)
#: Counts of a text, those of a block (the words of the first-order Reed-Muller code of that length are an anchor's
#: halves), rounds of signs and, from them, tables; factors that spread a shingle's hash, and weights of the counts of each factor.
COUNTS, BLOCK, ROUNDS, SPREAD, WEIGHTS = 4096, 512, 24, 4, (7, 8, 9, 10)
TABLES = ROUNDS * COUNTS // BLOCK // 2
#: Bits of a fingerprint that anchors compare and that groups compare, and the most that may differ for an exact check. At
#: an index of exactly 0.8 a bit differs with probability 0.1515, more than these with 3e-6 and 2e-6, and two texts meet
#: at no anchor with (1 - 0.1236)^96 = 3e-6.
BITS, RADIUS, WIDE_BITS, WIDE_RADIUS = 64, 24, 2048, 387
#: Tables of the first step, texts transformed at a time, texts of an anchor whose near pairs are listed, texts up to
#: which they are looked for; texts and shingles of a block of a group.
FIRST_TABLES, ROWS, LISTED, LOOKED, GROUP_ROWS, GROUP_SHINGLES = 12, 64, 64, 8192, 1024, 1 << 21


def text_fingerprint(text: str | None) -> int:
    """The SimHash of a text's word shingles: bit i is set if over half of the shingle hashes have it set."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined, n = b" ".join(words), max(1, len(words) - SHINGLE + 1)
    counts = np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    if n == 1:
        return digest(joined, SEED)
    length = np.fromiter(map(len, words), np.int64, len(words))
    start = np.cumsum(length + 1) - length - 1
    end = start + length
    for a in range(0, n, 1 << 16):
        b = min(n, a + (1 << 16))
        hashes = np.array([digest(joined[s:e], SEED) for s, e in zip(start[a:b].tolist(), end[a + SHINGLE - 1 : b + SHINGLE - 1].tolist(), strict=True)], ">u8")
        counts += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, h, fp): the text's hash and its fingerprint as a signed long. Texts without words have fingerprint 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            fp = np.array([text_fingerprint(t) for t in batch.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(fp.view(np.int64))], ["id", "h", "fp"])

    return short_batches(docs.select(id_col, text_col, F.xxhash64(text_col))).mapInArrow(run, f"id {docs.schema[id_col].dataType.simpleString()}, h bigint, fp bigint")


@lru_cache(maxsize=1)
def _cosets() -> tuple[np.ndarray, list[np.ndarray]]:
    """The syndrome of every 23-bit word by halves, and for each excess (0, 1, 2 over the radius) the error patterns by
    syndrome, padded with -1."""

    def remainder(word: int) -> int:
        for bit in range(_BITS - 1, 10, -1):
            if word >> bit & 1:
                word ^= _GENERATOR << (bit - 11)
        return word

    of_bit = [remainder(1 << i) for i in range(_BITS)]
    lists: list[list[list[int]]] = [[[] for _ in range(2048)] for _ in range(THRESHOLD + 1)]
    for weight in range(_RADIUS + THRESHOLD + 1):
        for bits in combinations(range(_BITS), weight):
            syndrome = pattern = 0
            for b in bits:
                syndrome ^= of_bit[b]
                pattern |= 1 << b
            lists[max(0, weight - _RADIUS)][syndrome].append(pattern)
    tables = []
    for group in lists:
        table = np.full((2048, max(map(len, group))), -1, np.int64)
        for s, patterns in enumerate(group):
            table[s, : len(patterns)] = patterns
        tables.append(table)
    halves = np.zeros((2, 4096), np.int64)
    for i in range(12):
        halves[0] ^= np.where(np.arange(4096) >> i & 1, of_bit[i], 0)
    for i in range(11):
        halves[1] ^= np.where(np.arange(4096) >> i & 1, of_bit[12 + i], 0)
    return halves, tables


def visits(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, anchor, home) of every anchor that each fingerprint must be sent to."""
    halves, tables = _cosets()
    parts = []
    for shift in (0, _BITS):
        word = (fp >> np.uint64(shift)).astype(np.int64) & ((1 << _BITS) - 1)
        syndrome = halves[0][word & 4095] ^ halves[1][word >> 12]
        codes = []
        for table in tables:
            error = table[syndrome]
            codes.append(np.where(error < 0, -1, (word[:, None] ^ error) >> 11))  # the upper 12 bits name the code word
        parts.append(codes)
    rows, anchors, homes = [], [], []
    for i in range(THRESHOLD + 1):
        for j in range(THRESHOLD + 1 - i):
            left, right = parts[0][i][:, :, None], parts[1][j][:, None, :]
            row, x, y = np.nonzero((left >= 0) & (right >= 0))
            rows.append(row)
            anchors.append(left[row, x, 0] << 12 | right[row, 0, y])
            homes.append(np.full(len(row), i == j == 0))
    return np.concatenate(rows), np.concatenate(anchors), np.concatenate(homes)


def components(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component) for the nodes of the links a-b."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    a, b = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while len(a):
        x, y = label[a], label[b]
        differ = x != y
        if not differ.any():
            break
        a, b, x, y = a[differ], b[differ], x[differ], y[differ]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while (label[label] != label).any():
            label = label[label]
    return nodes, nodes[label]


def _near(group: np.ndarray, fp: np.ndarray, home: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """Stars of the links between visitors and residents of each group; rows are sorted by group."""
    resident, lived = fp[home], group[home]
    low, high = np.searchsorted(lived, group, "left"), np.searchsorted(lived, group, "right")
    met = high - low
    ends = np.cumsum(met)
    stars: list[tuple[np.ndarray, np.ndarray]] = []
    at = 0
    while at < len(fp):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + CHUNK_PAIRS, "right")))
        count = met[at:to]
        if count.sum():
            visitor = np.repeat(np.arange(at, to), count)
            host = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(low[at:to], count)
            left, right = fp[visitor], resident[host]
            near = (left != right) & (np.bitwise_count((left ^ right).view(np.uint64)) <= THRESHOLD)
            if near.any():
                stars.append(components(left[near], right[near]))
        at = to
    return stars


def _linked(anchor: np.ndarray, fp: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stars of the links between visitors and residents of each anchor; rows are sorted by anchor."""
    names, number, size = np.unique(anchor, return_inverse=True, return_counts=True)
    hot = (size * np.bincount(number, home, len(names)) > SPLIT_PAIRS)[number]
    stars = _near(anchor[~hot], fp[~hot], home[~hot]) if not hot.all() else []
    if hot.any():
        number, word, own = number[hot], fp[hot], home[hot]
        for shift, bits in ((0, 21), (21, 21), (42, 22)):
            third = (word.view(np.uint64) >> np.uint64(shift)).astype(np.int64) & ((1 << bits) - 1)
            group = number << 22 | third
            order = np.argsort(group, kind="stable")
            stars += _near(group[order], word[order], own[order])
    if not stars:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    node, root = components(*(np.concatenate(x) for x in zip(*stars, strict=True)))
    return node[node != root], root[node != root]


def links(distinct: DataFrame) -> DataFrame:
    """(u, v): links, u > v, that connect what is connected by distances of at most two among distinct ``fp``."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, 4096):
            fp = batch.column("fp").to_numpy(zero_copy_only=False)
            row, anchor, home = visits(fp.view(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(anchor.astype(np.int32)), pa.array(fp[row]), pa.array(home)], ["anchor", "fp", "home"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []  # parts of whole anchors, and of one that goes on; joined once, when compared
        rows = 0

        def flush() -> pa.RecordBatch:
            node, root = _linked(*(np.concatenate(c) for c in zip(*held, strict=True)))
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(node), pa.array(root)], ["u", "v"])

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("anchor", "fp", "home")]
            rows += batch.num_rows
            cut = int(np.searchsorted(columns[0], columns[0][-1], "left"))  # the last anchor may go on
            goes_on = not cut and held and held[-1][0][-1] == columns[0][0]
            if rows >= CHUNK_ROWS and not goes_on:
                if cut:
                    held.append([c[:cut] for c in columns])
                if held:
                    yield flush()
                columns = [c[cut:] for c in columns]
                rows = len(columns[0])
            held.append(columns)
        if held:
            yield flush()

    sent = distinct.select("fp").mapInArrow(send, "anchor int, fp bigint, home boolean")
    return sent.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(compare, "u bigint, v bigint")


def connect(edges: DataFrame, one_task: int | None = None) -> DataFrame:
    """(u, root) for every node u with links, other than roots. Up to ``one_task`` links (ONE_TASK by default) are one
    task's work; beyond it large and small stars to the least neighbour alternate until nothing changes. Only a count
    and a checksum of the links reach the driver."""

    def star(e: DataFrame, large: bool) -> DataFrame:
        seen = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else e
        least = seen.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
        joined = seen.join(least, "u")
        if large:
            out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        else:
            out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
        return out.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[batch.column(c).to_numpy(zero_copy_only=False) for c in ("u", "v")] for batch in batches]
        if held:
            node, root = components(*(np.concatenate(x) for x in zip(*held, strict=True)))
            apart = node != root
            yield pa.RecordBatch.from_arrays([pa.array(node[apart]), pa.array(root[apart])], ["u", "root"])

    edges = checkpoint(edges.distinct())
    seen = mark(edges)
    if seen[0] <= (ONE_TASK if one_task is None else one_task):
        return checkpoint(edges.select("u", "v").coalesce(1).mapInArrow(whole, "u bigint, root bigint"))
    while seen[0]:
        edges = checkpoint(star(star(edges, True), False))
        now = mark(edges)
        if now == seen:
            break
        seen = now
    return edges.select("u", F.col("v").alias("root"))


def anchored_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, h, fp, root, component_id) for each row: the text's hash, the fingerprint, the component's least fingerprint,
    and the smallest id among all rows reachable over links.

    Equal fingerprints are linked; so are all texts without words, whose fingerprint is 0. A row with a null id takes
    part but names no component: a component without any id has a null component_id. Repeated rows are rows of one
    component; long texts are read whole; an empty table gives an empty result; other columns are not read.
    """
    marked = checkpoint(fingerprints(docs, id_col, text_col))
    nodes = checkpoint(marked.groupBy("fp").agg(F.min("id").alias("least")))
    roots = connect(links(nodes))
    rooted = nodes.join(roots, F.col("fp") == F.col("u"), "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    joined = marked.join(rooted.select("fp", "root").join(named, "root"), "fp")
    return joined.select(F.col("id").alias(id_col), "h", "fp", "root", "component_id")


def near_duplicate_digest(docs: DataFrame) -> DataFrame:
    return anchored_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def shingle_set(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of a text's five-word shingles; a shorter text is one shingle, one without words none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(b" ".join(words[i : i + WORDS]), SEED) for i in range(max(1, len(words) - WORDS + 1))], np.uint64))


@lru_cache(maxsize=1)
def _rounds() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A sign for each count and round (and for the round of the bits), the factors that spread a shingle's hash, and
    the Hadamard matrix of half the exponent."""
    rng = np.random.default_rng(SEED)
    side = np.arange(math.isqrt(COUNTS))
    hadamard = 1 - 2 * (np.bitwise_count(side[:, None] & side) & 1).astype(np.float32)
    return rng.integers(0, 2, (ROUNDS + 1, COUNTS)).astype(np.float32) * 2 - 1, rng.integers(0, 1 << 63, SPREAD, np.uint64) * np.uint64(2) + np.uint64(1), hadamard


def _counts(shingles: np.ndarray) -> np.ndarray:
    """Each shingle's signed weights, in the counts that they go to; whole numbers, so that no order of sums matters."""
    places, weights = [], []
    for at in range(0, len(shingles), 1 << 14):
        spread = (shingles[at : at + (1 << 14), None] * _rounds()[1]).ravel()
        for j, weight in enumerate(WEIGHTS):
            own = (spread >> np.uint64(64 - 13 * (j + 1))).view(np.int64)
            places.append(own >> 1 & (COUNTS - 1))
            weights.append(weight - 2.0 * weight * (own & 1))
    return np.bincount(np.concatenate(places), np.concatenate(weights), COUNTS) if places else np.zeros(COUNTS)


def wide_fingerprints(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(SimHash bits, anchor in each table) of sets of shingles. A round flips a text's counts by fixed signs; the
    Hadamard transform then gives each block's correlations with all words of the code (complements: the negative), and
    the nearest word is half an anchor. The bits are signs of sums over all counts. Equal sets have equal fingerprints."""
    signs, _, hadamard = _rounds()
    prints, anchors = np.empty((len(sets), WIDE_BITS // 8), np.uint8), np.empty((len(sets), TABLES), np.int32)
    for at in range(0, len(sets), ROWS):
        part = slice(at, at + ROWS)
        counts = np.array([_counts(s) for s in sets[part]], np.float32)
        for r in range(ROUNDS + 1):
            near = (hadamard @ (counts * signs[r]).reshape(-1, *hadamard.shape) @ hadamard).reshape(len(counts), -1, BLOCK)
            if r == ROUNDS:
                prints[part] = np.packbits(near.reshape(len(counts), -1)[:, :WIDE_BITS] > 0, axis=1)
                break
            word = np.abs(near).argmax(2)
            word = 2 * word + (np.take_along_axis(near, word[:, :, None], 2)[:, :, 0] < 0)
            table = np.arange(TABLES)[r * TABLES // ROUNDS : (r + 1) * TABLES // ROUNDS]
            anchors[part, table[0] : table[-1] + 1] = (table * 2 * BLOCK + word[:, ::2]) * 2 * BLOCK + word[:, 1::2]
    return prints, anchors


def _apart(a: np.ndarray, b: np.ndarray, n: np.ndarray, root: np.ndarray) -> np.ndarray:
    """Whether texts are in different components and not too different in size to be alike."""
    return (root[a] != root[b]) & (np.minimum(n[a], n[b]) * LEAST[1] >= np.maximum(n[a], n[b]) * LEAST[0])


def _meetings(anchor: np.ndarray, h: np.ndarray, n: np.ndarray, fp: np.ndarray, root: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a, b, group) of rows sorted by anchor: the places of near pairs at an anchor; or, where these are more than the
    anchor's texts, of stars that join them to a group (group is true). Texts of one group (``own``) are passed over."""
    start = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
    size = np.diff(np.r_[start, len(anchor)])
    number = np.repeat(np.arange(len(start)), size)
    near = lambda a, b: _apart(a, b, n, root) & (own[a] != own[b]) & (np.bitwise_count((fp[a] ^ fp[b]).view(np.uint64)) <= RADIUS)
    pairs = [(np.empty(0, np.int64),) * 2]
    a = np.flatnonzero(size[number] <= LISTED)
    for t in range(1, LISTED):
        a = a[a + t < len(anchor)]
        a = a[number[a] == number[np.minimum(a + t, len(anchor) - 1)]]
        if not len(a):
            break
        kept = a[near(a, a + t)]
        pairs.append((kept, kept + t))
    a, b = (np.concatenate(x) for x in zip(*pairs, strict=True))
    many = (np.bincount(number[a], minlength=len(start)) > size)[number[a]]
    stars = [components(a[many], b[many])]
    for i in np.flatnonzero(size > LISTED):
        places = np.arange(start[i], start[i] + size[i])
        if size[i] > LOOKED:
            stars.append((places, np.full(size[i], start[i])))
            continue
        found = []
        for at in range(0, size[i], 256):
            x, y = np.repeat(places[at : at + 256], size[i]), np.tile(places, len(places[at : at + 256]))
            x, y = x[x < y], y[x < y]
            kept = near(x, y)
            found.append(components(x[kept], y[kept]))
        stars.append(components(*(np.concatenate(x) for x in zip(*found, strict=True))))
    node, root = (np.concatenate(x) for x in zip(*stars, strict=True))
    node, root = node[node != root], root[node != root]
    return np.r_[a[~many], node], np.r_[b[~many], root], np.arange((~many).sum() + len(node)) >= (~many).sum()


def _meet(rows: DataFrame) -> DataFrame:
    """(a, b, grouped): near pairs, and links of groups, from (anchor, h, n, fp, root, own)."""
    names = ["anchor", "h", "n", "fp", "root", "own"]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []  # parts of whole anchors, and of one that goes on
        count = 0

        def flush() -> pa.RecordBatch:
            whole = [np.concatenate(c) for c in zip(*held, strict=True)]
            held.clear()
            whole[4:] = (c ^ whole[1] for c in whole[4:])
            a, b, grouped = _meetings(*whole)
            return pa.RecordBatch.from_arrays([pa.array(whole[1][a]), pa.array(whole[1][b]), pa.array(grouped)], ["a", "b", "grouped"])

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in names]
            count += batch.num_rows
            cut = int(np.searchsorted(columns[0], columns[0][-1], "left"))  # the last anchor may go on
            goes_on = not cut and held and held[-1][0][-1] == columns[0][0]
            if count >= CHUNK_ROWS and not goes_on:
                if cut:
                    held.append([c[:cut] for c in columns])
                if held:
                    yield flush()
                columns = [c[cut:] for c in columns]
                count = len(columns[0])
            held.append(columns)
        if held:
            yield flush()

    short = (F.col(c).bitwiseXOR(F.col("h")).alias(c) for c in names[4:])  # mostly zero, so that shuffles are small
    return rows.select(*names[:4], *short).repartition("anchor").sortWithinPartitions("anchor").mapInArrow(compare, "a bigint, b bigint, grouped boolean")


def _alike(x: np.ndarray, y: np.ndarray) -> bool:
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both * LEAST[1] >= (len(x) + len(y) - both) * LEAST[0]


def _group_links(members: DataFrame) -> DataFrame:
    """(u, v): links, u > v, that connect texts at least 0.8 alike in each group of (h, n, bits, s, root, own, blocks).
    Each block meets each other; of texts whose wide fingerprints are near, those not yet connected are checked."""
    keys = ["own", "first", "last"]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        key = lambda batch, i: tuple(batch.column(k)[i].as_py() for k in keys)

        def flush() -> pa.RecordBatch:
            table = pa.Table.from_batches(held)
            held.clear()
            h, n, label, block = (table.column(c).to_numpy() for c in ("h", "n", "root", "block"))
            label = label.copy()
            bits = np.frombuffer(b"".join(table.column("bits").to_pylist()), np.uint64).reshape(len(h), -1)
            sets = [np.frombuffer(x, np.uint64) for x in table.column("s").to_pylist()]
            first, last = table.column("first")[0].as_py(), table.column("last")[0].as_py()
            left, right = np.flatnonzero(block == first), np.flatnonzero(block == last)
            links = []
            for at, x in enumerate(left):
                others = right[at + 1 :] if first == last else right
                others = others[_apart(x, others, n, label)]
                for y in others[np.bitwise_count(bits[others] ^ bits[x]).sum(1, dtype=np.int64) <= WIDE_RADIUS]:
                    if label[x] != label[y] and _alike(sets[x], sets[y]):
                        links.append((max(h[x], h[y]), min(h[x], h[y])))
                        label[label == label[y]] = label[x]
            u, v = zip(*links, strict=True) if links else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

        for batch in batches:
            ends = [*(i for i in range(1, batch.num_rows) if key(batch, i) != key(batch, i - 1)), batch.num_rows]
            for s, e in zip([0, *ends], ends, strict=False):
                if held and e > s and key(held[-1], 0) != key(batch, s):
                    yield flush()
                if e > s:
                    held.append(batch.slice(s, e - s))
        if held:
            yield flush()

    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    sent = members.withColumn("block", F.pmod("h", F.col("blocks")).cast("int")).select("*", other)
    sent = sent.select("own", F.least("block", "other").alias("first"), F.greatest("block", "other").alias("last"), "block", "h", "n", "root", "bits", "s")
    return short_batches(sent.repartition(*keys).sortWithinPartitions(*keys, "h")).mapInArrow(compare, "u bigint, v bigint")


def _shingle_sets(texts: DataFrame) -> DataFrame:
    """(h, s): the shingle set of each text, once a hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingle_set(t).tobytes() for t in batch.column(1).to_pylist()], pa.binary())], ["h", "s"])

    once = texts.groupBy("h").agg(F.first("text").alias("text"))
    return short_batches(once.select("h", "text")).mapInArrow(run, "h bigint, s binary")


def _similar(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The (a, b) of ``pairs`` whose texts are at least 0.8 alike."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            near = [_alike(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)) for x, y in zip(batch.column("sa"), batch.column("sb"), strict=True)]
            kept = batch.filter(pa.array(near, pa.bool_()))
            yield pa.RecordBatch.from_arrays([kept.column("a"), kept.column("b")], ["a", "b"])

    side = lambda c: sets.select(F.col("h").alias(c), F.col("s").alias(f"s{c}"))
    return pairs.join(side("b"), "b").join(side("a"), "a").mapInArrow(compare, "a bigint, b bigint")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, h, root, component_id) for each row: the text's hash, the least such hash in the component, and the smallest
    id among all rows reachable over pairs of texts at least 0.8 alike. All texts without words are alike; null ids take
    part but name no component.

    Texts that meet at an anchor and whose fingerprints differ in few bits are checked exactly, first in a few tables, then
    in the others. Where an anchor has more near pairs than texts, as with many half-alike copies, these form a group instead. A
    group's texts are compared once, each block with each, by wider fingerprints, and only pairs that are near by these
    and not yet connected are checked. So no pair that is near at an anchor is left out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            sets = [shingle_set(t) for t in batch.column(1).to_pylist()]
            prints, anchors = wide_fingerprints(sets)
            bits = pa.array([p.tobytes() for p in prints], pa.binary())
            anchors = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * TABLES), pa.array(anchors.ravel()))
            fp = pa.array(prints[:, : BITS // 8].copy().view(np.int64)[:, 0])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([len(s) for s in sets], pa.int32()), fp, bits, anchors], ["id", "h", "n", "fp", "bits", "anchors"])

    id_type = docs.schema[id_col].dataType.simpleString()
    marked = checkpoint(short_batches(docs.select(id_col, text_col, F.xxhash64(text_col))).mapInArrow(run, f"id {id_type}, h bigint, n int, fp bigint, bits binary, anchors array<int>"))
    texts = docs.select(F.xxhash64(text_col).alias("h"), F.col(text_col).alias("text"))
    nodes = checkpoint(marked.groupBy("h").agg(F.min("id").alias("least"), *(F.first(c).alias(c) for c in ("n", "fp", "bits", "anchors"))))
    named = lambda df, of, to: df.join(of.select(F.col("u").alias("h"), F.col("root").alias(to)), "h", "left").withColumn(to, F.coalesce(to, "h"))

    shingled = lambda of: checkpoint(_shingle_sets(texts.join(of.select("h").distinct(), "h", "left_semi")))
    stars = lambda df: df.select("u", F.col("root").alias("v"))

    roots = groups = None
    for table, tables in ((1, FIRST_TABLES), (1 + FIRST_TABLES, TABLES - FIRST_TABLES)):
        at = nodes.select("h", "n", "fp", F.slice("anchors", table, tables).alias("anchors"))
        at = at.select("*", F.col("h").alias("root"), F.col("h").alias("own")) if roots is None else named(named(at, roots, "root"), groups, "own")
        met = checkpoint(_meet(at.withColumn("anchor", F.explode("anchors"))))
        pairs = checkpoint(met.where("not grouped").select("a", "b").distinct())
        found = _similar(pairs, shingled(pairs.select(F.explode(F.array("a", "b")).alias("h")))).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        roots = connect(found if roots is None else found.union(stars(roots)))
        joins = met.where("grouped").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        groups = connect(joins if groups is None else joins.union(stars(groups)))
        inside = groups.select(F.col("u").alias("h"), F.col("root").alias("own")).union(groups.select(F.col("root").alias("h"), F.col("root").alias("own")).distinct())
        if not inside.isEmpty() and not joins.isEmpty():
            inside = checkpoint(nodes.select("h", "n", "bits").join(inside, "h"))
            size = F.greatest(F.count("*") / GROUP_ROWS, F.sum(F.col("n").cast("long")) / GROUP_SHINGLES)
            inside = named(inside.join(inside.groupBy("own").agg(F.greatest(F.ceil(size), F.lit(1)).cast("int").alias("blocks")), "own"), roots, "root")
            roots = connect(_group_links(inside.join(shingled(inside), "h")).union(stars(roots)))
    rooted = nodes.join(roots.withColumnRenamed("u", "h"), "h", "left").select("h", "least", F.coalesce("root", "h").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    joined = marked.select("id", "h").join(rooted.select("h", "root").join(named, "root"), "h")
    return joined.select(F.col("id").alias(id_col), "h", "root", "component_id")


def drop_near_duplicates(docs: DataFrame, found: DataFrame | None = None) -> DataFrame:
    """One row of each component, with the columns of ``docs``: that with the smallest id, among rows of that id the one
    whose text's hash is least. A component without any id keeps the row whose text's hash is least. ``found`` has the
    rows' components, by default those of fingerprints within two bits."""
    found = anchored_duplicates(docs) if found is None else found
    rank = F.struct(F.col("doc_id").isNull().alias("n"), F.col("doc_id").alias("i"), F.col("h").alias("h"))
    key = lambda i, h: F.concat_ws(":", F.coalesce(i.cast("string"), F.lit("")), h).alias("key")  # noqa: E731  one column, so that the texts move once
    kept = found.groupBy("root").agg(F.min(rank).alias("m")).select(key(F.col("m.i"), F.col("m.h"))).distinct()
    own = docs.select(F.struct(*(f"`{c}`" for c in docs.columns)).alias("d"))  # apart from the names used here
    stay = own.select("d", key(F.col("d.doc_id"), F.xxhash64("d.text"))).join(kept, "key", "left_semi")
    nth = F.row_number().over(Window.partitionBy("key").orderBy(F.lit(0)))
    return stay.withColumn("nth", nth).where("nth = 1").select("d.*")
