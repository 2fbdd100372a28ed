"""Assembling samples, and the purge rules, key terms and filters that come before rating."""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.keys import order_key
from salvage.functions.materialize import checkpoint, spread

SAMPLE = ["sample_id", "component", "instruction", "input", "response"]

#: Purge rules: name, pattern, replacement, and literals of which every match holds one, so that a text without them is
#: not searched. The dialect is common to Java and RE2; runs are bounded where they could be searched again and again.
PURGE_RULES = [
    ("junk_suffix", r"(###|\*\*\*|%%%|&&&|\$\$\$)", "", ("###", "***", "%%%", "&&&", "$$$")),
    ("shouting", r"!!+", "", ("!!",)),
    ("secret", r'(token|key|secret|password) ?[=:] ?"[^"\n]{8,200}"', "<secret>", ('"',)),
    ("email", r"[A-Za-z0-9._-]{1,64}@[A-Za-z0-9.-]+", "<mail>", ("@",)),
    ("address", r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}", "<ip>", (".",)),
    ("phone", r"\+[0-9]{1,2} \([0-9]{3}\) [0-9]{3}-[0-9]{4}", "<phone>", ("+",)),
    ("link", r"https?://[^ \n]+", "<link>", ("://",)),
    ("markup", r"<[a-z/][^<>]{0,200}>", " ", (">",)),
    ("licence", r"(All rights reserved\.?|Licensed under the [A-Za-z0-9 ,.-]{0,200})", "", ("All rights reserved", "Licensed under")),
    ("pipes", r" \| ", " ", (" | ",)),
]
TERM = r"[a-zà-ÿ]+"


def samples_from_conversations(conv: DataFrame) -> DataFrame:
    """A sample for each user turn that an assistant turn follows; a system turn before it is the input."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    seen = conv.select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("next_text"), F.last(F.when(F.col("role") == "system", F.col("text")), ignorenulls=True).over(w).alias("system"))
    kept = seen.where("role = 'user' and next_role = 'assistant'")
    return kept.select((F.col("conv_id") * 1_048_576 + F.col("turn")).alias("sample_id"), F.lit("conversations").alias("component"), F.col("text").alias("instruction"), F.col("system").alias("input"), F.col("next_text").alias("response"))


def samples_from_documents(docs: DataFrame, components: int = 5) -> DataFrame:
    """First sentence to the rest; a text of one sentence gives no sample."""
    pattern = r"(?s)^([^.!?]*[.!?])\s+(.+)$"
    parts = docs.withColumn("i", F.regexp_extract("text", pattern, 1)).withColumn("r", F.regexp_extract("text", pattern, 2))
    component = F.concat(F.lit("documents-"), F.pmod(F.conv(F.substring(F.md5("source"), 1, 4), 16, 10).cast("int"), F.lit(components)))
    return parts.where("r <> ''").select(F.col("doc_id").alias("sample_id"), component.alias("component"), F.col("i").alias("instruction"), F.lit(None).cast("string").alias("input"), F.col("r").alias("response"))


def samples_from_pages(pages: DataFrame) -> DataFrame:
    """Title to paragraphs, without scripts, styles, navigation and comments."""
    body = F.col("html")
    for tag in ("script", "style", "nav"):
        body = F.regexp_replace(body, rf"(?s)<{tag}[^>]*>.*?</{tag}>", " ")
    body = F.regexp_replace(body, r"(?s)<!--.*?-->", " ")
    text = F.trim(F.regexp_replace(F.regexp_replace(F.regexp_extract(body, r"(?s)<article>(.*)</article>", 1), r"<[^>]*>", " "), r"[ \t\n\r]+", " "))
    title = F.regexp_extract("html", r"(?s)<title>(.*?)</title>", 1)
    return pages.select(F.col("page_id").alias("sample_id"), F.lit("pages").alias("component"), title.alias("instruction"), F.lit(None).cast("string").alias("input"), text.alias("response")).where("instruction <> '' and response <> ''")


def pool(*samples: DataFrame) -> DataFrame:
    """All samples in one table. Ids are unique within a family of components (conversations, documents, pages), so a row
    of the pool is named by ``pool_id``, family and id."""
    family = F.split_part(F.col("component"), F.lit("-"), F.lit(1))
    samples = [s.withColumn("pool_id", F.concat_ws(":", family, "sample_id")) for s in samples]
    out = samples[0]
    for s in samples[1:]:
        out = out.unionByName(s)
    return out


def take_quota(df: DataFrame, quota: int, seed: int = 42) -> DataFrame:
    """At most ``quota`` rows of each component, the first in md5 order; the limit is applied before the exchange."""
    rn = F.row_number().over(Window.partitionBy("component").orderBy(order_key("sample_id", seed), "sample_id"))
    return df.withColumn("_rn", rn).where(F.col("_rn") <= quota).drop("_rn")


def purge_text(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``df`` with purged text. A rule is a projection of its own: a text that an expression names several times is then
    computed once."""
    for _, pattern, repl, guards in PURGE_RULES:
        may = reduce(or_, (F.contains(F.col(text_col), F.lit(g)) for g in guards))
        df = df.withColumn(text_col, F.when(may, F.regexp_replace(text_col, pattern, repl)).otherwise(F.col(text_col)))
    return df.withColumn(text_col, F.trim(F.regexp_replace(text_col, r"[ ]+", " ")))


def purge(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``df`` with purged text and ``removed``, the hits by rule."""
    out, counts = df, []
    for i, (name, pattern, repl, guards) in enumerate(PURGE_RULES):  # column by column: a text that is used twice is computed once
        may = reduce(or_, (F.contains(F.col(text_col), F.lit(g)) for g in guards))
        hits = F.when(may, F.regexp_count(text_col, F.lit(pattern))).otherwise(0)
        out = out.withColumn(f"_hits{i}", hits).withColumn(text_col, F.when(F.col(f"_hits{i}") > 0, F.regexp_replace(text_col, pattern, repl)).otherwise(F.col(text_col)))
        counts += [F.lit(name), F.col(f"_hits{i}")]
    out = out.withColumn("removed", F.create_map(*counts)).withColumn(text_col, F.trim(F.regexp_replace(text_col, r"[ ]+", " ")))
    return out.drop(*(f"_hits{i}" for i in range(len(PURGE_RULES))))


def boilerplate(df: DataFrame, least: int = 5) -> DataFrame:
    """(line, n_texts): lines found in at least ``least`` different texts; copies of a text count once."""
    lines = df.select(F.xxhash64("text").alias("h"), F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("length(line) > 0")
    return lines.distinct().groupBy("line").agg(F.count("*").alias("n_texts")).where(F.col("n_texts") >= least)


def purge_lines(df: DataFrame, least: int = 5, id_col: str = "doc_id") -> DataFrame:
    """(id, text, n_removed): texts without boilerplate lines and without lines that repeat an earlier one of the text.

    Only lines that occur in two places at least can go, so texts are joined to those lines' hashes, not to all lines.
    """
    found = boilerplate(df, least).select(F.xxhash64("line").alias("h"))
    texts = df.select(F.col(id_col).alias("id"), F.split("text", "\n").alias("lines"))
    hit = texts.select("id", F.explode(F.array_distinct("lines")).alias("line")).select("id", F.xxhash64("line").alias("h"))
    drop = hit.join(found, "h", "left_semi").groupBy("id").agg(F.collect_set("h").alias("drop"))
    kept = F.filter("lines", lambda line, i: (line == "") | (~F.array_contains(F.coalesce("drop", F.array().cast("array<bigint>")), F.xxhash64(line)) & (F.array_position("lines", line) == i + 1)))
    out = texts.join(drop, "id", "left").withColumn("kept", kept)
    return out.select("id", F.array_join("kept", "\n").alias("text"), (F.size("lines") - F.size("kept")).alias("n_removed"))


def terms(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return spread(df.select(id_col, text_col)).select(F.col(id_col).alias("id"), F.explode(F.regexp_extract_all(F.lower(text_col), F.lit(TERM), 0)).alias("term"))


def key_terms(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", top: int = 10) -> DataFrame:
    """(id, term, score, place): the terms with the largest tf times idf."""
    tf = terms(df, id_col, text_col).groupBy("id", "term").agg(F.count("*").alias("tf"))
    idf = tf.groupBy("term").agg(F.count("*").alias("df"))
    n = df.agg(F.count("*").alias("n"))  # one row
    scored = tf.join(idf, "term").crossJoin(F.broadcast(n)).withColumn("score", F.round(F.col("tf") * F.log(F.col("n") / F.col("df")), 6))
    return scored.withColumn("place", F.row_number().over(Window.partitionBy("id").orderBy(F.desc("score"), "term"))).where(F.col("place") <= top).select("id", "term", "score", "place")


def dedup_exact(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(class_id, n): the smallest id and the number of the rows with one text."""
    return df.groupBy(F.md5(text_col).alias("h")).agg(F.min(id_col).alias("class_id"), F.count("*").alias("n")).select("class_id", "n")


def shingle_sets(df: DataFrame, n: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, s): distinct hashes of the word n-grams of each text with at least n words."""
    w = F.filter(F.split(F.lower(text_col), r"[ \t\n\r]+"), lambda x: x != "")
    shifted = F.arrays_zip(*(F.slice("w", i, F.size("w") - (n - 1)).alias(f"w{i}") for i in range(1, n + 1)))  # a lambda over w itself would split the text again for each word
    grams = F.transform(shifted, lambda z: F.xxhash64(F.concat_ws(" ", *(z[f"w{i}"] for i in range(1, n + 1)))))
    words = df.select(F.col(id_col).alias("id"), w.alias("w"))
    sets = words.select("id", F.when(F.size("w") >= n, F.array_sort(F.array_distinct(grams))).alias("s"))
    return sets.where("s is not null")


def dedup_near(df: DataFrame, threshold: float = 0.8, n: int = 5) -> tuple[DataFrame, DataFrame]:
    """Classes of equal shingle sets (id, class_id), and the pairs of classes (a, b, jaccard) that reach ``threshold``.

    Exact prefix filtering: two sets that reach the threshold share one of their few rarest shingles, so sets meet only
    over those; sets of too different sizes are not compared. Equal sets are one class and meet nobody twice.
    """
    sets = checkpoint(shingle_sets(spread(df.select("doc_id", "text")), n).withColumn("h", F.struct(F.xxhash64("s").alias("x"), F.xxhash64(F.lit(1), F.reverse("s")).alias("y"))))
    heads = sets.groupBy("h").agg(F.min("id").alias("class_id"))
    member = sets.select("id", "h").join(heads, "h").select("id", "class_id")
    classes = checkpoint(sets.join(heads.select(F.col("class_id").alias("id")), "id", "left_semi").select(F.col("id").alias("class_id"), "s"))
    exploded = classes.select("class_id", F.size("s").alias("len"), F.explode("s").alias("g"))
    rarity = exploded.groupBy("g").agg(F.count("*").alias("df"))
    ranked = exploded.join(rarity, "g").groupBy("class_id", "len").agg(F.array_sort(F.collect_list(F.struct("df", "g"))).alias("r"))
    keep = F.col("len") - F.ceil(F.col("len") * threshold - 1e-9).cast("int") + 1
    prefix = ranked.select("class_id", "len", F.explode(F.slice("r", F.lit(1), keep)).alias("x")).select("class_id", "len", F.col("x.g").alias("g"))
    x, y = prefix.alias("x"), prefix.alias("y")
    met = x.join(y, (F.col("x.g") == F.col("y.g")) & (F.col("x.class_id") < F.col("y.class_id")) & (F.least("x.len", "y.len") >= threshold * F.greatest("x.len", "y.len") - 1e-9))
    pairs = met.select(F.col("x.class_id").alias("a"), F.col("y.class_id").alias("b")).distinct()
    own = lambda k, s: classes.select(F.col("class_id").alias(k), F.col("s").alias(s))
    both = pairs.join(own("a", "sa"), "a").join(own("b", "sb"), "b").withColumn("i", F.size(F.array_intersect("sa", "sb")))
    jaccard = F.col("i") / (F.size("sa") + F.size("sb") - F.col("i"))
    return member, both.withColumn("jaccard", F.round(jaccard, 6)).where(jaccard >= threshold).select("a", "b", "jaccard")


def decontaminate(df: DataFrame, benchmark: DataFrame, n: int = 8) -> DataFrame:
    """``df`` without the rows that share a run of n words with a benchmark item."""
    grams = shingle_sets(benchmark, n, "item_id").select(F.explode("s").alias("g")).distinct()
    hit = shingle_sets(df, n).select("id", F.explode("s").alias("g")).join(grams, "g", "left_semi").select("id").distinct()
    return df.join(hit, df["doc_id"] == hit["id"], "left_anti")
