"""The offline text model: each operator of the loop as built-in expressions over sentences and terms.

A prompt is a value, struct<base_id, must_keep, must_drop, hints, version>, that the loop edits; it is rendered to text
only at a call of a hosted model. A loss is struct<keep, drop, missing, score>; score 0 accepts.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column
from pyspark.sql import functions as F

from salvage.functions.keys import let

PROMPT = "struct<base_id:string,must_keep:array<string>,must_drop:array<string>,hints:array<string>,version:int>"
LOSS = "struct<keep:array<string>,drop:array<string>,missing:array<string>,score:int>"
JUNK = r"(###|\*\*\*|%%%|&&&|\$\$\$|!!| \| )"
#: The same as plain strings, and a word of four or more letters.
MARKS, LONG_WORD = ("###", "***", "%%%", "&&&", "$$$", "!!", " | "), r"[a-zà-ÿ]{4,}"
#: Where a text ends its sentences.
STOP = r"[.!?]+[ \n]+|\n+"
#: Jaccard cut points of the relations, and sentences a first draft takes from each parent.
SAME, RELATED, LEAD = 0.30, 0.08, 2
#: What a patch adds to the hints of a prompt when a version carried noise; drafts then skip noisy sentences themselves.
NO_NOISE = "remove noise"

#: Relation, strategy, what it does, and the question of the merged row from the questions a and b of its parents.
STRATEGIES = [
    ("same", "S1", "union without repeats", "{a} {b}"),
    ("same", "S2", "compare the two and state differences", "Where do these two agree and differ: {a} / {b}"),
    ("same", "S3", "from the general statement to the detailed one", "Explain from the general to the particular: {a} {b}"),
    ("related", "S4", "connect through the shared terms", "How are these connected: {a} / {b}"),
    ("related", "S5", "use one as the example of the other", "Explain with an example: {a} {b}"),
    ("related", "S6", "order as background, then task", "Given the background, answer: {a} {b}"),
    ("unrelated", "S7", "one scenario that needs both", "In one situation with both: {a} {b}"),
    ("unrelated", "S8", "analogy between the two", "By analogy: {a} / {b}"),
    ("unrelated", "S9", "two-part question with a two-part answer", "Part one: {a} Part two: {b}"),
]


def sentences(text: Column) -> Column:
    return F.array_distinct(F.filter(F.transform(F.split(text, STOP), lambda s: F.trim(s)), lambda s: s != ""))


def long_words(text: Column) -> Column:
    """Words of four or more letters, as they come."""
    return F.regexp_extract_all(F.lower(text), F.lit(LONG_WORD), 0)


def term_set(text: Column) -> Column:
    """Distinct words of four or more letters, in order."""
    return F.sort_array(F.array_distinct(long_words(text)))


def jaccard(a: Column, b: Column) -> Column:
    union = F.size(F.array_union(a, b))
    return F.when(union > 0, F.size(F.array_intersect(a, b)) / union).otherwise(1.0)


def relate(terms_a: Column, terms_b: Column) -> Column:
    j = jaccard(terms_a, terms_b)
    return F.when(j >= SAME, "same").when(j >= RELATED, "related").otherwise("unrelated")


def is_junk(s: Column) -> Column:
    return reduce(or_, (F.contains(s, F.lit(mark)) for mark in MARKS))


def first_prompt(base_id: Column) -> Column:
    none = F.array().cast("array<string>")
    return F.struct(base_id.alias("base_id"), none.alias("must_keep"), none.alias("must_drop"), none.alias("hints"), F.lit(0).alias("version"))


def chosen(prompt: Column, sentences_: Column) -> Column:
    """Sentences of one parent for a draft: the leading ones and all that hold a term to keep, without those that an
    earlier version showed to be noise, and without any noisy one once the prompt asks for that."""
    keep = prompt["must_keep"]
    clean = F.filter(sentences_, lambda s: ~F.exists(prompt["must_drop"], lambda d: F.contains(d, s)) & ~(F.array_contains(prompt["hints"], F.lit(NO_NOISE)) & is_junk(s)))

    def taken(c: Column) -> Column:
        holds = F.filter(c, lambda s: F.arrays_overlap(long_words(s), keep))
        return F.when(F.size(keep) > 0, F.array_union(F.slice(c, 1, LEAD), holds)).otherwise(F.array_distinct(F.slice(c, 1, LEAD)))

    return let(clean, taken)


def arrange(strategy: Column, a: Column, b: Column) -> Column:
    """The sentences of a merged answer from those chosen of its parents, as each strategy orders and marks them."""
    mark = lambda word, x: F.transform(x, lambda s: F.concat(F.lit(word), s))
    both = F.array_union(a, b)
    by_length = F.transform(F.array_sort(F.transform(both, lambda s: F.struct(F.length(s).alias("n"), s.alias("s")))), lambda x: x["s"])
    shared = F.array_intersect(long_words(F.array_join(a, " ")), long_words(F.array_join(b, " ")))
    linked = let(shared, lambda terms: F.filter(both, lambda s: F.arrays_overlap(long_words(s), terms)))
    pairs = F.arrays_zip(a.alias("x"), b.alias("y"))
    in_turn = F.array_distinct(F.filter(F.flatten(F.transform(pairs, lambda p: F.array(p["x"], p["y"]))), lambda s: s.isNotNull()))
    likened = F.array_distinct(F.transform(pairs, lambda p: F.coalesce(F.concat(F.lit("As "), p["x"], F.lit(", so "), p["y"]), p["x"], p["y"])))
    return (
        F.when(strategy == "S1", both)
        .when(strategy == "S2", F.concat(F.array_intersect(a, b), mark("First: ", F.array_except(a, b)), mark("Second: ", F.array_except(b, a))))
        .when(strategy == "S3", by_length)
        .when(strategy == "S4", let(linked, lambda links: F.concat(links, F.array_except(both, links))))
        .when(strategy == "S5", F.concat(a, mark("For example: ", F.array_except(b, a))))
        .when(strategy == "S6", F.when(F.size(a) >= F.size(b), both).otherwise(F.array_union(b, a)))
        .when(strategy == "S7", in_turn)
        .when(strategy == "S8", likened)
        .when(strategy == "S9", F.concat(mark("Part one: ", a), mark("Part two: ", b)))
        .otherwise(F.concat(a, b))
    )


def draft(prompt: Column, a: Column, b: Column) -> Column:
    """Sentences of the merged answer in the manner of the prompt's strategy; without one they are just put together."""
    return arrange(prompt["base_id"], chosen(prompt, a), chosen(prompt, b))


def question(strategy: Column, a: Column, b: Column) -> Column:
    """The merged row's question by the strategy's template."""
    text = F.concat_ws(" ", a, b)
    for _, name, _, template in STRATEGIES:
        head, rest = template.split("{a}")
        middle, tail = rest.split("{b}")
        text = F.when(strategy == name, F.concat(F.lit(head), a, F.lit(middle), b, F.lit(tail))).otherwise(text)
    return text


def audit(answer: Column, wanted: Column) -> Column:
    """What a merged answer lacks of the wanted terms, and which of its sentences carry noise."""

    def loss(x: Column) -> Column:
        missing, noisy = x["missing"], x["drop"]
        return F.struct(x["keep"].alias("keep"), noisy.alias("drop"), missing.alias("missing"), (F.size(missing) + F.size(noisy)).alias("score"))

    noisy = F.filter(answer, is_junk)
    parts = lambda have: F.struct(F.array_intersect(wanted, have).alias("keep"), noisy.alias("drop"), F.array_except(wanted, have).alias("missing"))
    return let(let(term_set(F.array_join(answer, " ")), parts), loss)


def patch(prompt: Column, loss: Column) -> Column:
    """The next prompt: the loss's missing terms and noisy sentences are added, noise is asked to go, the version goes up."""
    hint = F.when(F.size(loss["drop"]) > 0, F.array(F.lit(NO_NOISE))).otherwise(F.array().cast("array<string>"))
    return F.struct(
        prompt["base_id"].alias("base_id"), F.array_union(prompt["must_keep"], loss["missing"]).alias("must_keep"), F.array_union(prompt["must_drop"], loss["drop"]).alias("must_drop"),
        F.array_union(prompt["hints"], hint).alias("hints"), (prompt["version"] + 1).alias("version"),
    )


def check_answer(asked: Column, answer: Column) -> Column:
    """Question terms that the answer leaves out, and its noisy sentences or plain copies of the question."""

    def loss(x: Column) -> Column:
        score = F.size(x["missing"]) + F.size(x["drop"]) + F.when(F.size(answer) == 0, 1).otherwise(0)
        return F.struct(x["keep"].alias("keep"), x["drop"].alias("drop"), x["missing"].alias("missing"), score.alias("score"))

    bad = F.filter(answer, lambda s: is_junk(s) | (s == asked))
    sets = F.struct(term_set(asked).alias("terms"), term_set(F.array_join(answer, " ")).alias("have"))
    parts = lambda t: F.struct(F.array_intersect(t["terms"], t["have"]).alias("keep"), bad.alias("drop"), F.array_except(t["terms"], t["have"]).alias("missing"))
    return let(let(sets, parts), loss)


def revise_answer(prompt: Column, answer: Column, parents: Column) -> Column:
    """The answer without what the prompt drops, and with the parents' clean sentences that hold its terms to keep."""
    stays = lambda s: ~F.array_contains(prompt["must_drop"], s)
    more = F.filter(parents, lambda s: F.arrays_overlap(long_words(s), prompt["must_keep"]) & stays(s) & ~is_junk(s))
    return F.array_union(F.filter(answer, stays), more)
