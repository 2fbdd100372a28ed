"""Packing token pieces into fixed windows by minimum bin slack.

A document's tokens are cut at every full window; full pieces are sequences of their own, and the remainders are
packed. A group of remainders is a multiset of lengths. A sequence starts with the longest one left; a subset-sum
dynamic program over bitsets then finds the multiset of lengths whose sum comes closest to the room left, and backtracks
how many of each length it holds. Sums that stop short of a full window may also end at a power of two, which needs no
padding. A bounded part of what a group can't pack well goes up to a group of groups, so that padding is left in few
sequences and no task grows with the input.
"""

from __future__ import annotations

import os
import re
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import blocks, checkpoint, short_batches

#: Remainders in a group, and groups that the next level joins.
GROUP_ROWS, FAN_IN = 8192, 16
#: The id at a document's end, and pieces of text whose ids a worker remembers.
END_ID, CACHE_PIECES = 1, 1 << 20
#: What the tokenizer's splitting pattern comes to on ASCII text, for a faster engine; tests compare the ids.
_ASCII = re.compile(r"'(?:s|t|re|ve|m|ll|d)| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+")


@lru_cache(maxsize=2)
def encoder(json_path: str):
    """A function from a text to its ids (uint32), as the tokenizer of the JSON file gives them.

    Its byte-level splitter cuts a text by a fixed pattern before any merge, and no merge crosses a cut; so the ids of a
    text are those of its pieces, each of which is encoded once and remembered. A text that spells out a special token
    goes to the tokenizer whole, which looks for those before it splits.
    """
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
    import public_tokenizers
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(json_path)
    special = [t.content for t in tokenizer.get_added_tokens_decoder().values()]
    split, split_ascii, known = regex.compile(public_tokenizers.PATTERN).findall, _ASCII.findall, {}

    def whole(text: str) -> list[int]:
        return tokenizer.encode(text, add_special_tokens=False).ids

    def encode(text: str) -> np.ndarray:
        if any(t in text for t in special):
            return np.array(whole(text), np.uint32)
        pieces = split_ascii(text) if text.isascii() else split(text)
        if new := list(set(pieces).difference(known)):
            if len(known) > CACHE_PIECES:
                known.clear()
                new = list(set(pieces))
            known.update(zip(new, (array("I", e.ids).tobytes() for e in tokenizer.encode_batch_fast(new, add_special_tokens=False)), strict=True))
        return np.frombuffer(b"".join(map(known.__getitem__, pieces)), np.uint32)

    return encode


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def cut_pieces(docs: DataFrame, json_path: str | None = None, room: int = 2048, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens[, ids]): a row for each piece of a document's tokens.

    A null or empty text has the end id as its only token; a long text gives as many pieces as it fills windows; rows
    that repeat an id or a text are documents of their own, as are rows with a null id. Other columns are not read.
    """
    json_path = json_path or tokenizer_path()
    names = [id_col, "start", "length", "ids_crc32", "doc_tokens"] + ["ids"] * keep_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(json_path)
        for batch in blocks(batches):
            at, start, length, crc, total, kept = [], [], [], [], [], []
            for i, text in enumerate(batch.column(1).to_pylist()):
                ids = np.append(encode(text or ""), np.uint32(END_ID))
                for a in range(0, len(ids), room):
                    piece = ids[a : a + room].astype("<u4")
                    at.append(i)
                    start.append(a)
                    length.append(len(piece))
                    crc.append(zlib.crc32(piece.tobytes()))
                    total.append(len(ids))
                    if keep_ids:
                        kept.append(piece)
            arrays = [batch.column(0).take(pa.array(at, pa.int64())), *(pa.array(x, pa.int64()) for x in (start, length, crc, total))]
            yield pa.RecordBatch.from_arrays(arrays + [pa.array(kept, pa.list_(pa.uint32())).cast(pa.list_(pa.int64()))] * keep_ids, names)

    kind = docs.schema[id_col].dataType.simpleString()
    out = f"`{id_col}` {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint" + ", ids array<bigint>" * keep_ids
    return short_batches(docs.select(id_col, text_col)).mapInArrow(run, out)


def fullest(lengths: list[int], counts: dict[int, int], room: int) -> dict[int, int]:
    """How many of each length the fullest multiset of at most ``room`` holds. ``lengths`` are distinct and descending.

    Bit s of ``reached`` says that s is a sum; each step doubles the copies it tries, so a count c costs log c shifts.
    """
    mask, reached, steps = (1 << (room + 1)) - 1, 1, []
    for length in lengths:
        if length > room:
            continue
        left, copies = min(counts[length], room // length), 1
        while left:
            take = min(copies, left)
            steps.append((length, take, reached))
            reached |= (reached << (length * take)) & mask
            left -= take
            copies *= 2
        if reached >> room & 1:
            break
    total, chosen = reached.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            total -= length * take
            chosen[length] = chosen.get(length, 0) + take
    return chosen


def pack_lengths(lengths: np.ndarray, room: int, slack: int = 0, hand_up: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece; sequence -1 for pieces that are handed up.

    Sequences with more padding than ``slack`` are handed up, the worst first, until ``hand_up`` pieces are, and one
    sequence in any case; those that remain stay as the best fill that their pieces allow. With ``hand_up`` 0 all are kept. A kept sequence that is not
    full is cut down to a power of two where its pieces can hit one exactly.
    """
    waiting: dict[int, list[int]] = {}
    for i, n in enumerate(lengths.tolist()):
        waiting.setdefault(n, []).append(i)
    order = sorted(waiting, reverse=True)
    counts = {n: len(x) for n, x in waiting.items()}
    made: list[tuple[int, list[int]]] = []
    while order:
        first = order[0]
        counts[first] -= 1
        room_left = room - first
        chosen = fullest(order, counts, room_left) if room_left else {}
        filled = first + sum(n * c for n, c in chosen.items())
        if not hand_up and filled < room:
            size = 1 << (filled.bit_length() - 1)
            while filled != size and size >= first:  # a smaller power of two that is hit exactly
                part = fullest(order, counts, size - first)
                if first + sum(n * c for n, c in part.items()) == size:
                    chosen, filled = part, size
                    break
                size >>= 1
        counts[first] += 1
        chosen[first] = chosen.get(first, 0) + 1
        held = [waiting[n].pop() for n in sorted(chosen, reverse=True) for _ in range(chosen[n])]
        for n, c in chosen.items():
            counts[n] -= c
        made.append((room - filled, held))
        order = [n for n in order if counts[n]]
    handed, up = set(), 0
    for at in sorted(range(len(made)), key=lambda x: -made[x][0]) if hand_up else []:
        padding, held = made[at]
        if padding <= slack or handed and up + len(held) > hand_up:
            break
        handed.add(at)
        up += len(held)
    sequence, offset, number = np.full(len(lengths), -1), np.zeros(len(lengths), np.int64), 0
    for at, (_, held) in enumerate(made):
        if at in handed:
            continue
        place = 0
        for i in held:
            sequence[i], offset[i] = number, place
            place += int(lengths[i])
        number += 1
    return sequence, offset


def pack_pieces(pieces: DataFrame, room: int = 2048, group_rows: int = GROUP_ROWS, fan_in: int = FAN_IN, slack: int = 0) -> DataFrame:
    """``pieces`` (with ``length``) and sequence_id, offset.

    Groups of remainders follow from the row's number, never from a key, so no group is hot. A level keeps the sequences
    whose padding is at most ``slack`` tokens and hands up at most a ``fan_in``th of a group's rows, those of its worst
    sequences, or a single sequence; so a group of any level, the last one too, has about ``group_rows`` rows. The last level packs all.
    Sequence ids are unique but not gapless: level, group and number in it. An empty table gives an empty result.
    """
    names = [c for c in pieces.columns if c not in ("sequence_id", "offset")]
    pieces = checkpoint(pieces.select(*names, F.monotonically_increasing_id().alias("_n")))
    short = F.col("length") < room
    n = pieces.where(short).count()
    groups = max(1, -(-n // group_rows))
    whole = pieces.where(~short).withColumn("sequence_id", -1 - F.col("_n")).withColumn("offset", F.lit(0).cast("long"))
    level = pieces.where(short).withColumn("_group", F.pmod(F.xxhash64("_n"), F.lit(groups)))
    parts, depth = [whole.select(*names, "sequence_id", "offset")], 0

    def packer(depth: int, hand_up: int):
        def run(rows: pa.Table) -> pa.Table:
            rows = rows.sort_by([(c, "ascending") for c in ("length", "_n")])
            sequence, offset = pack_lengths(rows.column("length").to_numpy(), room, slack, hand_up)
            sid = np.where(sequence < 0, -1, sequence + (rows.column("_group")[0].as_py() << 24) + (depth << 56))
            return rows.append_column("sequence_id", pa.array(sid, pa.int64())).append_column("offset", pa.array(offset, pa.int64()))

        return run

    while True:
        last = groups == 1
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in level.schema.fields)
        packed = checkpoint(level.groupBy("_group").applyInArrow(packer(depth, 0 if last else max(1, group_rows // fan_in)), fields + ", sequence_id bigint, offset bigint"))
        parts.append(packed.where("sequence_id >= 0").select(*names, "sequence_id", "offset"))
        if last:
            break
        groups, depth = -(-groups // fan_in), depth + 1
        level = packed.where("sequence_id < 0").drop("sequence_id", "offset").withColumn("_group", F.floor(F.col("_group") / fan_in))
    done = parts[0]
    for part in parts[1:]:
        done = done.union(part)
    return done


def pack_documents(docs: DataFrame, json_path: str | None = None, room: int = 2048) -> DataFrame:
    """The pieces of all documents with their sequences and offsets; see cut_pieces and pack_pieces for the edge cases."""
    return pack_pieces(cut_pieces(docs, json_path, room), room).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
