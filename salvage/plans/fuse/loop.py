"""The two cycles, each a bounded number of rounds over the rows that are still open."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from salvage.functions.keys import order_key
from salvage.functions.materialize import checkpoint
from salvage.functions.scratch import scratch
from salvage.plans.fuse import rules
from salvage.plans.fuse.backends import TextModel
from salvage.plans.fuse.operators import ModelOperators, RuleOperators
from salvage.plans.samples import purge_text


@dataclass(frozen=True)
class Options:
    """Switches of the ablations, and how often a version may be generated again in each cycle."""

    max_regen: int = 3
    cycle1: bool = True
    cycle2: bool = True
    strategies: bool = True
    purge: bool = True


def _words(text: Column) -> Column:
    return F.size(F.split(text, " "))


def _trace(df: DataFrame, cycle: int, iteration: int, op: str, loss: Column, tokens_in: Column, tokens_out: Column) -> DataFrame:
    return df.select("pair_id", F.lit(cycle).alias("cycle"), F.lit(iteration).alias("iter"), F.lit(op).alias("op"), F.col("prompt.version").alias("prompt_version"), loss.alias("loss"), tokens_in.alias("tokens_in"), tokens_out.alias("tokens_out"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return out


def _done(versions: DataFrame) -> bool:
    """No pair is open, so later rounds would have no row."""
    return versions.where("loss.score > 0").isEmpty()


def _best(versions: list[DataFrame]) -> DataFrame:
    """The version of each pair with the least loss, the earliest of equals."""
    return _union(versions).groupBy("pair_id").agg(F.min_by("v", F.struct("v.score", "v.iter")).alias("v"))


def pick_strategy(pair_id: Column) -> Column:
    """Which of a relation's three strategies a pair takes, 1 to 3."""
    return F.pmod(F.conv(F.substring(F.md5(pair_id), 1, 6), 16, 10).cast("int"), F.lit(3)) + 1


def prepared(pairs: DataFrame, options: Options = Options()) -> DataFrame:
    """(pair_id, a, b, sa, sb, wa, wb, wanted, qa, qb): sentences and terms of both parents, after the purge rules, the
    terms to keep (those of clean sentences) and each parent's first clean sentence."""
    texts = pairs.select("pair_id", "a", "b", F.coalesce("text_a", F.lit("")).alias("ta"), F.coalesce("text_b", F.lit("")).alias("tb"))
    if options.purge:
        texts = purge_text(purge_text(texts, "ta"), "tb")
    clean = lambda s: F.filter(s, lambda x: ~rules.is_junk(x))
    parts = checkpoint(texts).select("pair_id", "a", "b", rules.sentences(F.col("ta")).alias("sa"), rules.sentences(F.col("tb")).alias("sb"), rules.term_set(F.col("ta")).alias("wa"), rules.term_set(F.col("tb")).alias("wb"))
    first = lambda s: F.coalesce(F.try_element_at(clean(F.col(s)), F.lit(1)), F.lit(""))
    return parts.select("*", rules.term_set(F.array_join(F.concat(clean(F.col("sa")), clean(F.col("sb"))), " ")).alias("wanted"), first("sa").alias("qa"), first("sb").alias("qb"))


def fuse(pairs: DataFrame, options: Options = Options(), model: TextModel | None = None, cache: str | None = None, traced: bool = True) -> tuple[DataFrame, DataFrame | None]:
    """Merged rows and (unless not ``traced``) the trace of all calls, for ``pairs`` (pair_id, a, b, text_a, text_b).

    Cycle 1 drafts, audits and patches its prompt until the loss is 0 or the regenerations are used up; the version with
    the least loss (the earliest of equals) goes on. Cycle 2 checks the answer and revises it; the loss of a version
    drives the next prompt, so the best prompt is that of the round before. Each round is written before it is read
    again, so no call is repeated; only open rows take part. All terms of both parents' clean sentences are audited, and
    a patch asks for all that are missing. Rows without an accepted version are kept as exhausted.

    Operators are the rules, or prompts to ``model``, whose calls are kept in the folder ``cache`` (a new one by default)
    and replayed from it.
    """
    ops = RuleOperators() if model is None else ModelOperators(model, cache or scratch(pairs.sparkSession, "calls"))
    start = ops.relate(checkpoint(prepared(pairs, options)))
    offered = F.filter(F.array(*(F.struct(F.lit(r).alias("r"), F.lit(s).alias("s")) for r, s, _, _ in rules.STRATEGIES)), lambda x: x["r"] == F.col("relation"))
    strategy = F.element_at(offered, pick_strategy(F.col("pair_id")))["s"] if options.strategies else F.lit("none")
    asked = F.trim(F.concat_ws(" ", "qa", "qb"))
    work = start.withColumn("strategy", strategy).withColumn("question", asked).withColumn("prompt", rules.first_prompt(F.col("strategy")))
    work = checkpoint(work.select("pair_id", "a", "b", "sa", "sb", "qa", "qb", "relation", "strategy", "wanted", "question", "prompt"))
    whole = _words(F.array_join(F.concat("sa", "sb"), " "))
    traces = [_trace(work, 0, 0, "relate", F.lit(0), whole, F.lit(1))]

    versions, open_ = [], work
    for i in range(options.max_regen + 1 if options.cycle1 else 1):
        drafted = checkpoint(ops.audit(checkpoint(ops.draft(open_)) if model else ops.draft(open_)))
        out = _words(F.array_join("answer", " "))
        traces += [_trace(drafted, 1, i, "draft", F.col("loss.score"), whole + F.size("prompt.must_keep"), out), _trace(drafted, 1, i, "audit", F.col("loss.score"), out, F.size("loss.missing") + F.size("loss.drop"))]
        versions.append(drafted.select("pair_id", F.struct(F.col("loss.score").alias("score"), F.lit(i).alias("iter"), "answer", "prompt").alias("v")))
        if not options.cycle1 or _done(drafted):
            break
        open_ = drafted.where("loss.score > 0").withColumn("prompt", rules.patch(F.col("prompt"), F.col("loss"))).drop("answer", "loss")
    best = _best(versions)
    carried = work.drop("prompt").join(best, "pair_id").select("pair_id", "a", "b", "relation", "strategy", "question", "qa", "qb", F.array_union("sa", "sb").alias("parents"), F.col("v.answer").alias("answer"), F.col("v.score").alias("loss1"), F.col("v.prompt").alias("prompt"))
    carried = checkpoint(carried)

    finals, open_ = [], carried
    for i in range(options.max_regen + 1 if options.cycle2 else 1):
        checked = checkpoint(ops.check(open_) if options.cycle2 else RuleOperators().check(open_))
        if options.cycle2:
            traces.append(_trace(checked, 2, i, "check", F.col("loss.score"), _words(F.array_join("answer", " ")), F.size("loss.missing") + F.size("loss.drop")))
        finals.append(checked.select("pair_id", F.struct(F.col("loss.score").alias("score"), F.lit(i).alias("iter"), "answer", "prompt").alias("v")))
        if not options.cycle2 or i == options.max_regen or _done(checked):
            break
        revised = checked.where("loss.score > 0").withColumn("prompt", rules.patch(F.col("prompt"), F.col("loss"))).drop("loss")
        open_ = checkpoint(ops.revise(revised))
        traces.append(_trace(open_, 2, i, "revise", F.lit(None).cast("int"), _words(F.array_join("parents", " ")), _words(F.array_join("answer", " "))))
    asked = rules.question(F.col("strategy"), F.col("qa"), F.col("qb"))
    accepted = (F.col("loss1") == 0) & (F.col("v.score") == 0)
    merged = carried.drop("answer", "prompt").join(_best(finals), "pair_id").select(
        F.concat(F.lit("m:"), "pair_id").alias("merged_id"), "pair_id", F.array("a", "b").alias("parents"), "relation", "strategy", asked.alias("user"), F.array_join("v.answer", ". ").alias("assistant"),
        "loss1", F.col("v.score").alias("loss2"), F.when(accepted, "accepted").otherwise("exhausted").alias("status"),
    )
    return checkpoint(merged), checkpoint(_union(traces)) if traced else None


def fuse_clusters(reps: DataFrame, texts: DataFrame, options: Options = Options(), model: TextModel | None = None, cache: str | None = None) -> tuple[DataFrame, DataFrame, int]:
    """One merged text a cluster, by rounds of a tree: neighbours of the seed order are merged, an odd one is carried on.

    ``reps`` is (cluster_id, sample_id), ``texts`` (sample_id, text). The number of rounds, about log of the largest
    cluster, is driven by one count a round. Returns the last texts (cluster_id, item, text, leaves), all merges with the
    ``leaves`` (sample ids) they stand on and their ``round``, and the number of rounds.
    """
    place = F.row_number().over(Window.partitionBy("cluster_id").orderBy(order_key("sample_id"), "sample_id")) - 1
    items = reps.select("cluster_id", "sample_id").join(texts, "sample_id")
    items = checkpoint(items.select("cluster_id", place.alias("pos"), F.col("sample_id").cast("string").alias("item"), "text", F.array("sample_id").alias("leaves")))
    merges, rounds = [], 0
    while not items.groupBy("cluster_id").count().where("count > 1").isEmpty():
        rounds += 1
        slot, one = items.withColumn("slot", F.expr("pos div 2")), F.struct("item", "text", "leaves")
        sides = checkpoint(slot.groupBy("cluster_id", "slot").agg(F.min_by(one, "pos").alias("x"), F.max_by(one, "pos").alias("y"), F.count("*").alias("n")))
        pairs = sides.where("n = 2").select(F.concat_ws(":", F.lit(rounds), "cluster_id", "slot").alias("pair_id"), F.col("x.item").alias("a"), F.col("y.item").alias("b"), F.col("x.text").alias("text_a"), F.col("y.text").alias("text_b"), F.concat("x.leaves", "y.leaves").alias("leaves"), "cluster_id", "slot")
        merged, _ = fuse(pairs, options, model, cache, traced=False)
        with_leaves = merged.join(pairs.select("pair_id", "cluster_id", "slot", "leaves"), "pair_id")
        merges.append(with_leaves.select(*merged.columns, "cluster_id", "leaves", F.lit(rounds).alias("round")))
        after = with_leaves.select("cluster_id", F.col("slot").alias("pos"), F.col("merged_id").alias("item"), F.concat_ws("\n", "user", "assistant").alias("text"), "leaves")
        single = sides.where("n = 1").select("cluster_id", F.col("slot").alias("pos"), "x.item", "x.text", "x.leaves")
        items = checkpoint(after.union(single))
    if not merges:
        merges = [fuse(items.limit(0).selectExpr("item as pair_id", "item as a", "item as b", "text as text_a", "text as text_b"), options)[0].select("*", F.lit(0).cast("bigint").alias("cluster_id"), F.array().cast("array<bigint>").alias("leaves"), F.lit(0).alias("round"))]
    return items.select("cluster_id", "item", "text", "leaves"), _union(merges), rounds
