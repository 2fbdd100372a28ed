"""Licence detection by ordered signature rules.

A text becomes its words, joined by one blank. A rule is a regular expression over those words, filed under a keyword
that every match contains; a rule runs only in texts that hold its keyword. Detections are then taken in order of
priority, length and place, and one that lies inside the interval of an accepted detection is suppressed, so the precise
name of a licence hides the vague mention inside it. Base phrases are counted apart and never suppressed. Word numbers
come from one array of blanks and containment from a tree of interval ends, so a text of nothing but licence phrases
costs about as much a word as any other.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import blocks, short_batches

#: ASCII letters and digits and everything beyond ASCII make words; A-Z become a-z.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))

# The base phrases and their labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))


@dataclass(frozen=True)
class Signature:
    """``pattern`` is matched on whole words; ``keyword`` is a part of every match; higher ``priority`` goes first."""

    label: str
    pattern: str
    keyword: str
    priority: int
    confidence: float
    compiled: re.Pattern = field(compare=False, hash=False)


def _signature(label: str, pattern: str, keyword: str, priority: int, confidence: float) -> Signature:
    return Signature(label, pattern, keyword, priority, confidence, re.compile(rb" (?:" + pattern.encode() + rb")(?= )"))


def _version(v: str) -> str:
    """``3.0`` may be written 3, 3 0, v3, v 3 0, version 3 or version 3 0; other minor numbers must be there."""
    major, _, minor = v.partition(".")
    return rf"(?:v ?|version )?{major}" + (" 0" if minor == "" else "(?: 0)?" if minor == "0" else f" {minor}")


@lru_cache(maxsize=1)
def signatures() -> tuple[Signature, ...]:
    """Several hundred rules: hand-written forms for each licence family and version."""
    rules: list[Signature] = []
    add = lambda *a: rules.append(_signature(*a))
    # GNU family: named with a version, "or later", "only", the short name, the bare name.
    gnu = (("gpl", "general public license", "1.0 2.0 3.0"), ("lgpl", "(?:lesser|library) general public license", "2.0 2.1 3.0"), ("agpl", "affero general public license", "1.0 3.0"), ("gfdl", "free documentation license", "1.1 1.2 1.3"))
    for short, name, versions in gnu:
        key = "documentation license" if short == "gfdl" else "public license"
        for v in versions.split():
            n = _version(v)
            add(f"{short}-{v}-or-later", rf"(?:the )?(?:gnu )?{name} (?:as published by the free software foundation )?(?:either )?{n}(?: of the license)? or (?:at your option )?(?:any )?later(?: version)?", key, 95, 0.99)
            add(f"{short}-{v}-only", rf"(?:the )?(?:gnu )?{name} {n} only", key, 94, 0.98)
            add(f"{short}-{v}", rf"(?:the )?(?:gnu )?{name} {n}", key, 90, 0.95)
            add(f"{short}-{v}-or-later", rf"(?:gnu )?{short} ?{n} or later", short, 93, 0.97)
            add(f"{short}-{v}-only", rf"(?:gnu )?{short} ?{n} only", short, 92, 0.97)
            add(f"{short}-{v}", rf"(?:gnu )?{short} ?{n}", short, 85, 0.9)
        add(short, rf"(?:the )?gnu {name}", key, 60, 0.85)
        add(short, rf"gnu {short}", short, 55, 0.8)
    # Creative Commons: six kinds, five versions, long and short forms.
    kinds = (("by", "attribution"), ("by-sa", "attribution share ?alike"), ("by-nd", "attribution no ?deriv(?:ative)?s"), ("by-nc", "attribution non ?commercial"), ("by-nc-sa", "attribution non ?commercial share ?alike"), ("by-nc-nd", "attribution non ?commercial no ?deriv(?:ative)?s"))
    for kind, name in kinds:
        short = kind.replace("-", " ")
        for v in "1.0 2.0 2.5 3.0 4.0".split():
            n = _version(v)
            add(f"cc-{kind}-{v}", rf"creative commons {name} {n}(?: (?:international|unported|generic))?(?: license)?", "creative commons", 90, 0.98)
            add(f"cc-{kind}-{v}", rf"cc {short} {n}", "cc by", 88, 0.96)
            add(f"cc-{kind}-{v}", rf"creativecommons org licenses {short} {v.replace('.', ' ')}", "creativecommons org", 92, 0.99)
        add(f"cc-{kind}", rf"creative commons {name}(?: license)?", "creative commons", 62, 0.9)
        if kind != "by":
            add(f"cc-{kind}", rf"cc {short}", "cc by", 60, 0.88)
    add("cc0-1.0", r"cc0(?: 1 0)?(?: universal)?", "cc0", 80, 0.9)
    add("cc0-1.0", r"cc zero(?: 1 0)?(?: universal)?", "cc zero", 80, 0.9)
    add("cc0-1.0", r"creativecommons org publicdomain zero 1 0", "creativecommons org", 92, 0.99)
    # Named licences with versions: long name, abbreviation, SPDX tag.
    named = (
        ("apache", "apache(?: software)? license", "apache", "1.0 1.1 2.0"), ("mpl", "mozilla public license", "mozilla", "1.0 1.1 2.0"), ("epl", "eclipse public license", "eclipse", "1.0 2.0"),
        ("cddl", "common development and distribution license", "common development", "1.0 1.1"), ("cpl", "common public license", "common public", "1.0"), ("eupl", "european union public licen[cs]e", "european union", "1.0 1.1 1.2"),
        ("afl", "academic free license", "academic free", "1.1 1.2 2.0 2.1 3.0"), ("osl", "open software license", "open software", "1.0 2.0 2.1 3.0"), ("artistic", "artistic license", "artistic", "1.0 2.0"), ("bsl", "boost software license", "boost", "1.0"),
        ("lppl", "latex project public license", "latex project", "1.0 1.1 1.2 1.3"), ("ofl", "(?:sil )?open font license", "open font", "1.0 1.1"), ("ecl", "educational community license", "educational community", "1.0 2.0"),
        ("ms-pl", "microsoft public license", "microsoft", "1.0"), ("upl", "universal permissive license", "universal permissive", "1.0"), ("odbl", "open database license", "open database", "1.0"), ("odc-by", "open data commons attribution license", "open data commons", "1.0"),
        ("cecill", "cecill(?: free software)?(?: license)?", "cecill", "1.0 1.1 2.0 2.1"), ("zpl", "zope public license", "zope", "1.1 2.0 2.1"), ("php", "php license", "php", "3.0 3.01"), ("blue-oak", "blue oak model license", "blue oak", "1.0"),
    )
    for label, name, key, versions in named:
        for v in versions.split():
            n = _version(v)
            add(f"{label}-{v}", rf"(?:the )?{name} {n}", key, 90, 0.97)
            add(f"{label}-{v}", rf"spdx license identifier {label.replace('-', ' ')} {v.replace('.', ' ')}", "spdx", 96, 0.99)
        add(label, rf"(?:the )?{name}", key, 60, 0.85)
    # Licences known by name or by their grant text.
    plain = (
        ("mit", r"(?:the )?mit license", "mit license", 0.95), ("mit", r"permission is hereby granted free of charge to any person obtaining a copy", "hereby granted", 0.97), ("isc", r"(?:the )?isc license", "isc license", 0.95),
        ("isc", r"permission to use copy modify and or distribute this software for any purpose with or without fee", "with or without fee", 0.97), ("bsd-2-clause", r"(?:simplified|2 clause|two clause) bsd(?: license)?|bsd 2 clause(?: license)?", "bsd", 0.95),
        ("bsd-3-clause", r"(?:modified|new|3 clause|three clause) bsd(?: license)?|bsd 3 clause(?: license)?", "bsd", 0.95), ("bsd-4-clause", r"(?:original|4 clause|four clause) bsd(?: license)?|bsd 4 clause(?: license)?", "bsd", 0.95),
        ("bsd", r"bsd license", "bsd license", 0.85), ("bsd", r"redistribution and use in source and binary forms", "redistribution and use", 0.85), ("zlib", r"(?:the )?zlib(?: libpng)? license", "zlib", 0.95), ("unlicense", r"(?:the )?unlicense", "unlicense", 0.9), ("unlicense", r"free and unencumbered software released into the public domain", "unencumbered", 0.9),
        ("wtfpl", r"wtfpl", "wtfpl", 0.95), ("wtfpl", r"do what the fuck you want to public license", "you want to", 0.95), ("python-2.0", r"python software foundation license(?: version 2)?", "python software", 0.95), ("openssl", r"openssl license", "openssl", 0.95), ("postgresql", r"postgresql licen[cs]e", "postgresql", 0.95),
        ("ncsa", r"university of illinois ncsa open source license", "ncsa", 0.95), ("sspl-1.0", r"server side public license(?: v?1)?", "server side", 0.95), ("busl-1.1", r"business source license(?: 1 1)?", "business source", 0.95), ("elastic-2.0", r"elastic license(?: 2 0)?", "elastic license", 0.9),
        ("public-domain", r"(?:released into|in|dedicated to) the public domain", "public domain", 0.8), ("proprietary", r"proprietary and confidential|confidential and proprietary", "proprietary", 0.8), ("no-redistribution", r"(?:may|shall) not be (?:reproduced|redistributed|copied)", "not be", 0.6),
        ("copyright-notice", r"copyright(?: c)? \d{4}(?: \d{4})?(?: by)?", "copyright", 0.5), ("copyright-notice", r"©(?: copyright)? \d{4}(?: \d{4})?(?: by)?", "©", 0.5), ("licensed-under", r"licensed under the [^ ]+(?: [^ ]+)? licen[cs]e", "licensed under", 0.6),
    )
    for label, pattern, key, confidence in plain:
        add(label, pattern, key, 50 if confidence > 0.6 else 20, confidence)
    for label in "mit isc zlib unlicense wtfpl bsd-2-clause bsd-3-clause bsd-4-clause ncsa cc0-1.0 gpl-2.0-only gpl-3.0-only gpl-2.0-or-later gpl-3.0-or-later lgpl-2.1-only lgpl-3.0-only agpl-3.0-only agpl-3.0-or-later".split():
        add(label, "spdx license identifier " + re.sub(r"[-.]", " ", label), "spdx", 96, 0.99)
    return tuple(rules)


def words_of(text: str | None) -> bytes:
    """The words of a text, joined and bordered by one blank."""
    return b" " + b" ".join((text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()) + b" "


def _blanks(words: bytes) -> np.ndarray:
    """Places of the blanks; word i stands after blank i."""
    return np.flatnonzero(np.frombuffer(words, np.uint8) == 32)


def base_places(words: bytes, blanks: np.ndarray | None = None) -> list[tuple[str, int]]:
    """Label and first word of every place of a base phrase."""
    blanks, found = _blanks(words) if blanks is None else blanks, []
    for phrase, label in BASE:
        needle, at, hits = f" {phrase} ".encode(), -1, []
        while (at := words.find(needle, at + 1)) >= 0:
            hits.append(at)
        found += [(label, i) for i in np.searchsorted(blanks, hits).tolist()]
    return sorted(found, key=lambda x: (x[1], x[0]))


class _Reach:
    """The furthest end among intervals that start at or before a word: prefix maxima in a binary indexed tree."""

    def __init__(self, starts: np.ndarray):
        self.starts, self.ends = starts, [-1] * (len(starts) + 1)

    def upto(self, place: int) -> int:
        far = -1
        while place > 0:
            far = max(far, self.ends[place])
            place &= place - 1
        return far

    def add(self, place: int, end: int) -> None:
        while place < len(self.ends):
            if self.ends[place] < end:
                self.ends[place] = end
            place += place & -place


def detect(words: bytes, rules: tuple[Signature, ...] | None = None, blanks: np.ndarray | None = None) -> list[tuple[str, int, int, int, float]]:
    """Accepted detections (label, first word, end word, priority, confidence) in order of place."""
    held: dict[str, bool] = {}
    blanks, hits = _blanks(words) if blanks is None else blanks, []
    for rule in signatures() if rules is None else rules:
        if (here := held.get(rule.keyword)) is None:
            here = held[rule.keyword] = rule.keyword.encode() in words
        if here and (spans := [m.span() for m in rule.compiled.finditer(words)]):
            for first, end in np.searchsorted(blanks, np.array(spans)).tolist():  # a match begins at a blank and ends before one
                hits.append((rule.label, first, end, rule.priority, rule.confidence))
    hits.sort(key=lambda h: (-h[3], h[1] - h[2], h[1], h[0]))
    starts = np.unique([h[1] for h in hits])
    places = (np.searchsorted(starts, [h[1] for h in hits]) + 1).tolist()
    reach, taken = _Reach(starts), []
    for h, place in zip(hits, places, strict=True):
        if reach.upto(place) < h[2]:
            taken.append(h)
            reach.add(place, h[2])
    return sorted(taken, key=lambda h: (h[1], h[2], h[0]))


_SPAN = pa.struct([("label", pa.string()), ("first", pa.int64()), ("end", pa.int64()), ("priority", pa.int32()), ("confidence", pa.float64())])
_PLACE = pa.struct([("label", pa.string()), ("first", pa.int64())])


def scan_licenses(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, n_words, base (places of base phrases) and detections (accepted rule matches, as word intervals).

    A null or empty text has no words; every row gives one row, repeated rows and null ids too; an empty table gives an
    empty result; other columns are not read. Of equal detections the first label in order is kept. Long texts are read
    whole, in time that grows with their length; memory is bounded by a block of texts.
    """
    names = [id_col, "n_words", "base", "detections"]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            counts, places, spans = [], [], []
            for text in batch.column(1).to_pylist():
                words = words_of(text)
                blanks = _blanks(words)
                counts.append(max(0, len(blanks) - 1) if len(words) > 2 else 0)
                places.append([{"label": a, "first": b} for a, b in base_places(words, blanks)])
                spans.append([dict(zip(("label", "first", "end", "priority", "confidence"), d, strict=True)) for d in detect(words, blanks=blanks)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(places, pa.list_(_PLACE)), pa.array(spans, pa.list_(_SPAN))], names)

    kind = df.schema[id_col].dataType.simpleString()
    span, place = "struct<label:string,first:bigint,end:bigint,priority:int,confidence:double>", "struct<label:string,first:bigint>"
    return short_batches(df.select(id_col, text_col)).mapInArrow(scan, f"`{id_col}` {kind}, n_words bigint, base array<{place}>, detections array<{span}>")


def license_digest(docs: DataFrame) -> DataFrame:
    """One row a document: counts and places of base phrases, the labels, and the chance that some licence is there."""
    found = scan_licenses(docs)
    joined = lambda c: F.array_join(F.array_sort(F.array_distinct(c)), ",")
    sure = F.aggregate("detections.confidence", F.lit(1.0), lambda a, c: a * (1 - c))
    return found.select(
        "doc_id", "n_words", F.size("base").cast("long").alias("n_base"), F.array_min("base.first").alias("first_word"), F.array_max("base.first").alias("last_word"),
        joined(F.col("base.label")).alias("base_labels"), joined(F.concat("base.label", "detections.label")).alias("labels"),
        F.round(1 - sure * F.when(F.size("base") > 0, 0.1).otherwise(1.0), 9).alias("score"), "detections",
    )
