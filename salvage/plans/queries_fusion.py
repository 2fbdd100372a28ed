"""Queries over pairing, the fuse loop, its traces and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from salvage.functions.keys import order_key, order_key_sql
from salvage.functions.scratch import scratch
from salvage.plans import metrics, pairing, representatives
from salvage.plans.chain import Chain, low_documents, with_texts
from salvage.plans.fixtures import LOW_SQL, PAIRS_SQL, given_vectors
from salvage.plans.fuse import rules
from salvage.plans.fuse.backends import EchoModel, TextModel, ask, call, replay
from salvage.plans.fuse.loop import Options, fuse, pick_strategy, prepared
from salvage.plans.queries_clusters import _CELLS, _CHOSEN, _cells
from salvage.plans.queries_samples import purged_sql
from salvage.registry import query, read


def _reps(spark, sf):
    return representatives.choose(*_cells(spark, sf)).select("sample_id", "cluster_id")


@query("intra_plan", f"WITH RECURSIVE {_CHOSEN}, m AS (SELECT cluster_id, count(*) AS m FROM reps GROUP BY 1) SELECT cluster_id, r.r::INT AS round, l.l::INT AS left, (l.l + (1 << (r.r - 1)))::INT AS right FROM m, range(1, 12) r(r), range(0, 2000) l(l) WHERE l.l % (1 << r.r) = 0 AND l.l + (1 << (r.r - 1)) < m AND l.l < m")
def intra_plan(spark, sf):
    return pairing.intra_plan(_reps(spark, sf))


@query("intra_plan_fold", f"WITH {_CHOSEN}, m AS (SELECT cluster_id, count(*) AS m FROM reps GROUP BY 1) SELECT cluster_id, r.r::INT AS round, 0 AS left, r.r::INT AS right FROM m, range(1, 2000) r(r) WHERE r.r < m")
def intra_plan_fold(spark, sf):
    return pairing.intra_plan(_reps(spark, sf), "fold")


def _ring_sql(inside: str) -> str:
    return f"WITH {_CHOSEN}, o AS (SELECT sample_id, cluster_id, {order_key_sql('sample_id')} AS ord FROM reps), i AS (SELECT *, {inside} AS inside FROM o), p AS (SELECT *, row_number() OVER (ORDER BY inside, ord, sample_id) - 1 AS pos FROM i) SELECT x.sample_id AS a, y.sample_id AS b, x.cluster_id AS cluster_a, y.cluster_id AS cluster_b FROM p x JOIN p y ON y.pos = x.pos + 1 AND x.pos % 2 = 0 WHERE x.cluster_id <> y.cluster_id"


@query("inter_pairs_ring", _ring_sql("row_number() OVER (PARTITION BY cluster_id ORDER BY ord, sample_id)"))
def inter_pairs_ring(spark, sf):
    return pairing.inter_pairs(_reps(spark, sf))


@query("inter_pairs_random", _ring_sql("0"))
def inter_pairs_random(spark, sf):
    return pairing.inter_pairs(_reps(spark, sf), "random")


def _other_sql(order: str) -> str:
    return f"WITH {_CHOSEN}, {PAIRS_SQL}, s AS (SELECT sims.a, sims.b, x.cluster_id AS cluster_a, y.cluster_id AS cluster_b, sims.s FROM sims JOIN reps x ON x.sample_id = a JOIN reps y ON y.sample_id = b WHERE x.cluster_id <> y.cluster_id) SELECT a, b, cluster_a, cluster_b FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s {order}, b) AS r FROM s) WHERE r = 1"


def _other(spark, sf, pairing_):
    reps = _reps(spark, sf)
    vectors = given_vectors(spark, sf).select("sample_id", "vec").join(reps, "sample_id").select("sample_id", "cluster_id", "vec")
    return pairing.inter_pairs(reps, pairing_, vectors=vectors)


@query("inter_pairs_nearest", _other_sql("DESC"))
def inter_pairs_nearest(spark, sf):
    return _other(spark, sf, "nearest_other")


@query("inter_pairs_farthest", _other_sql("ASC"))
def inter_pairs_farthest(spark, sf):
    return _other(spark, sf, "farthest_other")


@query("fusion_account", f"WITH {_CHOSEN}, m AS (SELECT cluster_id, count(*) AS m FROM reps GROUP BY 1), k AS (SELECT 'intra' AS config, sum(m - 1)::BIGINT AS n FROM m UNION ALL SELECT 'inter', (SELECT count(*) FROM ({_ring_sql('row_number() OVER (PARTITION BY cluster_id ORDER BY ord, sample_id)')}))) SELECT config, sum(n)::BIGINT AS n FROM k GROUP BY GROUPING SETS ((config), ())")
def fusion_account(spark, sf):
    reps = _reps(spark, sf)
    intra = pairing.intra_plan(reps).agg(F.count("*").alias("n")).select(F.lit("intra").alias("config"), "n")
    inter = pairing.inter_pairs(reps).agg(F.count("*").alias("n")).select(F.lit("inter").alias("config"), "n")
    return intra.union(inter).groupingSets([["config"], []], "config").agg(F.sum("n").alias("n"))


#: The loop in SQL, for pairs of low documents that follow each other in the random order: the same operators over lists.
def _terms(text: str) -> str:
    return f"list_sort(list_distinct(list_filter(regexp_extract_all(lower({text}), '[a-zà-ÿ]+'), lambda t: length(t) >= 4)))"


def _uniq(x: str) -> str:
    """Distinct elements in order of first place."""
    return f"list_filter({x}, lambda e, i: list_position({x}, e) = i)"


def _sents(text: str) -> str:
    parts = f"list_filter(list_transform(regexp_split_to_array({text}, '[.!?]+[ \n]+|\n+'), lambda s: trim(s)), lambda s: s <> '')"
    return _uniq(parts)


_JUNK = "regexp_matches({}, '" + rules.JUNK + "')"
_LOOP = f"""{LOW_SQL}, lo AS (SELECT *, row_number() OVER (ORDER BY {order_key_sql('sample_id')}, sample_id) - 1 AS pos FROM low),
lp AS (SELECT x.sample_id || '-' || y.sample_id AS pair_id, x.text AS xa, y.text AS xb FROM lo x JOIN lo y ON x.pos % 2 = 0 AND y.pos = x.pos + 1),
pu AS (SELECT pair_id, {purged_sql('xa')} AS ta, {purged_sql('xb')} AS tb FROM lp),
se AS (SELECT pair_id, {_sents('ta')} AS sa, {_sents('tb')} AS sb, {_terms('ta')} AS wa, {_terms('tb')} AS wb FROM pu),
cl0 AS (SELECT *, list_filter(sa, lambda s: NOT {_JUNK.format('s')}) AS ka, list_filter(sb, lambda s: NOT {_JUNK.format('s')}) AS kb FROM se),
wk AS (SELECT *, {_terms("array_to_string(list_concat(ka, kb), ' ')")} AS wanted, coalesce(ka[1], '') AS qa, coalesce(kb[1], '') AS qb,
  CASE WHEN len(list_distinct(list_concat(wa, wb))) = 0 THEN 1.0 ELSE len(list_intersect(wa, wb)) / len(list_distinct(list_concat(wa, wb))) END AS j FROM cl0),
rl AS (SELECT *, CASE WHEN j >= {rules.SAME} THEN 'same' WHEN j >= {rules.RELATED} THEN 'related' ELSE 'unrelated' END AS relation, ('0x' || substr(md5(pair_id), 1, 6))::INT % 3 AS pick FROM wk),
w0 AS (SELECT *, 'S' || (CASE relation WHEN 'same' THEN 1 WHEN 'related' THEN 4 ELSE 7 END + pick) AS strategy, trim(qa || ' ' || qb) AS question, len(string_split(array_to_string(list_concat(sa, sb), ' '), ' ')) AS whole FROM rl)"""


def _chosen_sql(x: str) -> str:
    clean = f"list_filter({x}, lambda s: len(list_filter(must_drop, lambda d: contains(d, s))) = 0 AND NOT (noisy AND {_JUNK.format('s')}))"
    return _uniq(f"list_concat(({clean})[1:{rules.LEAD}], list_filter({clean}, lambda s: list_has_any({_terms('s')}, must_keep)))")


def _arranged_sql() -> str:
    both = _uniq("list_concat(ca, cb)")
    shared = f"list_intersect({_terms(chr(39).join(['array_to_string(ca, ', ' ', ')']))}, {_terms(chr(39).join(['array_to_string(cb, ', ' ', ')']))})"
    links = f"list_filter({both}, lambda s: list_has_any({_terms('s')}, {shared}))"
    except_ = lambda x, y: f"list_filter({x}, lambda s: NOT list_contains({y}, s))"
    mark = lambda word, x: f"list_transform({x}, lambda s: '{word}' || s)"
    turns = _uniq("list_filter(flatten(list_transform(range(greatest(len(ca), len(cb))), lambda i: [ca[i + 1], cb[i + 1]])), lambda s: s IS NOT NULL)")
    likened = _uniq("list_transform(range(greatest(len(ca), len(cb))), lambda i: coalesce('As ' || ca[i + 1] || ', so ' || cb[i + 1], ca[i + 1], cb[i + 1]))")
    return f"""CASE strategy WHEN 'S1' THEN {both}
 WHEN 'S2' THEN list_concat(list_concat(list_filter(ca, lambda s: list_contains(cb, s)), {mark('First: ', except_('ca', 'cb'))}), {mark('Second: ', except_('cb', 'ca'))})
 WHEN 'S3' THEN list_transform(list_sort(list_transform({both}, lambda s: {{'n': length(s), 's': s}})), lambda x: x.s)
 WHEN 'S4' THEN list_concat({links}, list_filter({both}, lambda s: NOT list_has_any({_terms('s')}, {shared})))
 WHEN 'S5' THEN list_concat(ca, {mark('For example: ', except_('cb', 'ca'))})
 WHEN 'S6' THEN CASE WHEN len(ca) >= len(cb) THEN {both} ELSE {_uniq('list_concat(cb, ca)')} END
 WHEN 'S7' THEN {turns} WHEN 'S8' THEN {likened}
 ELSE list_concat({mark('Part one: ', 'ca')}, {mark('Part two: ', 'cb')}) END"""


def _drafts_sql(rounds: int) -> str:
    """CTEs a0, a1, ...: the audited drafts of each round, open rows only."""
    out, none = [], "[]::VARCHAR[]"
    for i in range(rounds):
        prompt = f"w0.*, {none} AS must_keep, {none} AS must_drop, false AS noisy FROM w0" if i == 0 else f"w0.*, {_uniq('list_concat(p.must_keep, p.missing)')} AS must_keep, {_uniq('list_concat(p.must_drop, p.bad)')} AS must_drop, p.noisy OR len(p.bad) > 0 AS noisy FROM w0 JOIN a{i - 1} p USING (pair_id) WHERE p.score > 0"
        out.append(f"p{i} AS (SELECT {prompt}), c{i} AS (SELECT *, {_chosen_sql('sa')} AS ca, {_chosen_sql('sb')} AS cb FROM p{i}), d{i} AS (SELECT *, {_arranged_sql()} AS answer FROM c{i}), h{i} AS (SELECT *, {_terms(chr(39).join(['array_to_string(answer, ', ' ', ')']))} AS have, list_filter(answer, lambda s: {_JUNK.format('s')}) AS bad FROM d{i}), a{i} AS (SELECT *, len(missing) + len(bad) AS score FROM (SELECT *, list_filter(wanted, lambda t: NOT list_contains(have, t)) AS missing FROM h{i}))")
    return ", ".join(out)


_ROUNDS = 4
_WORDS = "len(string_split(array_to_string({}, ' '), ' '))"
_CYCLE1 = f"WITH RECURSIVE {_LOOP}, {_drafts_sql(_ROUNDS)}, audits AS (" + " UNION ALL ".join(f"SELECT pair_id, {i} AS iter, score, answer, must_keep, len(missing) + len(bad) AS said, whole, {_WORDS.format('answer')} AS words FROM a{i}" for i in range(_ROUNDS)) + ")"
_TRACE1 = "SELECT pair_id, 1 AS cycle, iter, op, iter AS prompt_version, score::INT AS loss, (CASE op WHEN 'draft' THEN whole + len(must_keep) ELSE words END)::INT AS tokens_in, (CASE op WHEN 'draft' THEN words ELSE said END)::INT AS tokens_out FROM audits, (VALUES ('draft'), ('audit')) o(op)"


def low_pairs(spark, sf):
    """Low documents in the random order, two at a time, with their texts."""
    texts = low_documents(spark, sf).select(F.col("doc_id").alias("sample_id"), "text")
    placed = pairing.global_position(texts.select("sample_id"), order_key("sample_id"), F.col("sample_id"))
    sides = placed.groupBy(F.expr("pos div 2").alias("at")).agg(F.min_by("sample_id", "pos").alias("a"), F.max_by("sample_id", "pos").alias("b"), F.count("*").alias("n"))
    return with_texts(sides.where("n = 2").select("a", "b"), texts)


def _related(spark, sf):
    """The prepared pairs with relation, strategy, question and first prompt."""
    rows = prepared(low_pairs(spark, sf)).withColumn("jaccard", rules.jaccard(F.col("wa"), F.col("wb"))).withColumn("relation", rules.relate(F.col("wa"), F.col("wb")))
    number = F.when(F.col("relation") == "same", 0).when(F.col("relation") == "related", 3).otherwise(6) + pick_strategy(F.col("pair_id"))
    rows = rows.withColumn("strategy", F.concat(F.lit("S"), number)).withColumn("question", F.trim(F.concat_ws(" ", "qa", "qb")))
    return rows.withColumn("prompt", rules.first_prompt(F.col("strategy")))


def _drafted(spark, sf):
    from salvage.plans.fuse.operators import RuleOperators

    ops = RuleOperators()
    return ops.audit(ops.draft(_related(spark, sf)))


@query("relate_pairs", f"WITH RECURSIVE {_LOOP} SELECT pair_id, round(j, 6) AS jaccard, relation FROM w0")
def relate_pairs(spark, sf):
    return _related(spark, sf).select("pair_id", F.round("jaccard", 6).alias("jaccard"), "relation")


_TABLE = "strategies(relation, strategy, template) AS (VALUES " + ", ".join(str((r, s, t)) for r, s, t, _ in rules.STRATEGIES) + ")"


@query("strategy_lookup", f"WITH RECURSIVE {_LOOP}, {_TABLE} SELECT pair_id, relation, s.strategy AS strategy, template, s.strategy = w0.strategy AS taken FROM w0 JOIN strategies s USING (relation)")
def strategy_lookup(spark, sf):
    """The three strategies that each pair is offered, and the one that the rules take."""
    table = F.broadcast(spark.createDataFrame([(r, s, t) for r, s, t, _ in rules.STRATEGIES], "relation string, strategy string, template string"))
    return _related(spark, sf).select("pair_id", "relation", F.col("strategy").alias("own")).join(table, "relation").select("pair_id", "relation", "strategy", "template", (F.col("strategy") == F.col("own")).alias("taken"))


@query("draft_rule", f"WITH RECURSIVE {_LOOP}, {_drafts_sql(1)} SELECT pair_id, strategy, len(answer) AS n_sentences, md5(array_to_string(answer, '|')) AS answer FROM a0")
def draft_rule(spark, sf):
    """First drafts of pairs of low documents, each in the manner of its strategy."""
    return _drafted(spark, sf).select("pair_id", "strategy", F.size("answer").cast("bigint").alias("n_sentences"), F.md5(F.array_join("answer", "|")).alias("answer"))


_ALL = " UNION ALL ".join(f"SELECT * REPLACE ('S{k}' AS strategy) FROM w0" for k in range(1, 10))


@query("draft_strategies", f"WITH RECURSIVE {_LOOP.replace('w0 AS (SELECT', 'w00 AS (SELECT')}, w0 AS ({_ALL.replace('w0', 'w00')}), {_drafts_sql(1)} SELECT pair_id, strategy, md5(array_to_string(answer, '|')) AS answer FROM a0")
def draft_strategies(spark, sf):
    """The first draft of every pair in the manner of each of the nine strategies."""
    from salvage.plans.fuse.operators import RuleOperators

    nine = F.explode(F.array(*(F.lit(s) for _, s, _, _ in rules.STRATEGIES)))
    rows = _related(spark, sf).drop("strategy", "prompt").withColumn("strategy", nine).withColumn("prompt", rules.first_prompt(F.col("strategy")))
    return RuleOperators().draft(rows).select("pair_id", "strategy", F.md5(F.array_join("answer", "|")).alias("answer"))


@query("audit_loss", f"WITH RECURSIVE {_LOOP}, {_drafts_sql(1)} SELECT pair_id, len(missing) AS missing, len(wanted) - len(missing) AS keep, len(bad) AS bad, score FROM a0")
def audit_loss(spark, sf):
    """The audit of first drafts."""
    n = lambda c: F.size(c).cast("bigint")
    return _drafted(spark, sf).select("pair_id", n("loss.missing").alias("missing"), n("loss.keep").alias("keep"), n("loss.drop").alias("bad"), F.col("loss.score").cast("bigint").alias("score"))


@query("patch_prompt", f"WITH RECURSIVE {_LOOP}, {_drafts_sql(1)} SELECT pair_id, 1 AS version, strategy AS base_id, md5(array_to_string(missing, ',')) AS must_keep, len(bad) AS n_drop FROM a0")
def patch_prompt(spark, sf):
    p = rules.patch(F.col("prompt"), F.col("loss"))
    return _drafted(spark, sf).withColumn("p", p).select("pair_id", "p.version", "p.base_id", F.md5(F.array_join("p.must_keep", ",")).alias("must_keep"), F.size("p.must_drop").cast("bigint").alias("n_drop"))


_CHECK = f"k AS (SELECT *, list_filter({_terms('question')}, lambda t: NOT list_contains(have, t)) AS gap, list_filter(answer, lambda s: {_JUNK.format('s')} OR s = question) AS worse FROM h0), ck AS (SELECT *, len(gap) + len(worse) + (len(answer) = 0)::INT AS loss2 FROM k)"


@query("check_answer", f"WITH RECURSIVE {_LOOP}, {_drafts_sql(1)}, {_CHECK} SELECT pair_id, len(gap) AS missing, loss2 AS score FROM ck")
def check_answer(spark, sf):
    """The check of first drafts against their questions."""
    loss = rules.check_answer(F.col("question"), F.col("answer"))
    return _drafted(spark, sf).withColumn("check", loss).select("pair_id", F.size("check.missing").cast("bigint").alias("missing"), F.col("check.score").cast("bigint").alias("score"))


_PARENTS = _uniq("list_concat(sa, sb)")


@query("revise_answer", f"WITH RECURSIVE {_LOOP}, {_drafts_sql(1)}, r AS (SELECT pair_id, {_uniq(f'list_concat(answer, list_filter({_PARENTS}, lambda s: list_has_any({_terms(chr(115))}, missing) AND NOT ' + _JUNK.format('s') + '))')} AS revised FROM a0) SELECT pair_id, len(revised) AS n_sentences, md5(array_to_string(revised, '|')) AS answer FROM r")
def revise_answer(spark, sf):
    """First drafts, revised for the terms that the audit missed."""
    rows = _drafted(spark, sf).withColumn("p", rules.patch(F.col("prompt"), F.col("loss"))).withColumn("revised", rules.revise_answer(F.col("p"), F.col("answer"), F.array_union("sa", "sb")))
    return rows.select("pair_id", F.size("revised").cast("bigint").alias("n_sentences"), F.md5(F.array_join("revised", "|")).alias("answer"))


@query("cycle1_trace", f"{_CYCLE1} {_TRACE1}")
def cycle1_trace(spark, sf):
    """Drafts and audits of the pairs of low documents, round by round."""
    return fuse(low_pairs(spark, sf))[1].where("cycle = 1")


@query("cycle1_best", f"{_CYCLE1} SELECT pair_id, arg_min(iter, (score, iter))::INT AS best_iter, min(score)::INT AS loss, count(*) AS versions FROM audits GROUP BY 1")
def cycle1_best(spark, sf):
    """The version that goes on: least loss, earliest of equals."""
    audits = fuse(low_pairs(spark, sf))[1].where("cycle = 1 and op = 'audit'")
    return audits.groupBy("pair_id").agg(F.min_by("iter", F.struct("loss", "iter")).alias("best_iter"), F.min("loss").alias("loss"), F.count("*").alias("versions"))


@query("trace_loss_curve", f"{_CYCLE1} SELECT iter, count(*) AS open, round(avg(score), 6) AS mean_loss, count(*) FILTER (WHERE score = 0) AS accepted FROM audits GROUP BY 1")
def trace_loss_curve(spark, sf):
    """Mean loss and accepted rows by draft."""
    trace = fuse(low_pairs(spark, sf))[1].where("op = 'audit'")
    return trace.groupBy("iter").agg(F.count("*").alias("open"), F.round(F.avg("loss"), 6).alias("mean_loss"), F.count_if(F.col("loss") == 0).alias("accepted"))


# On the chain: all that follows reads the estimated correction, the cells and the representatives.


@query("fuse_inter")
def fuse_inter(spark, sf):
    merged = Chain(spark, sf).inter()
    return merged.select("merged_id", "parents", "relation", "strategy", "status", "loss1", "loss2", F.length("assistant").alias("n_chars"))


@query("fuse_intra")
def fuse_intra(spark, sf):
    """Representatives of each cluster merged until one is left: every merge."""
    return Chain(spark, sf).intra().select("cluster_id", "round", "merged_id", "relation", "strategy", "status", F.size("leaves").alias("n_leaves"), F.length("assistant").alias("n_chars"))


@query("cycle2_trace")
def cycle2_trace(spark, sf):
    return Chain(spark, sf).trace().where("cycle = 2")


@query("fuse_summary")
def fuse_summary(spark, sf):
    merged = Chain(spark, sf).inter()
    return merged.groupBy("relation", "strategy", "status").agg(F.count("*").alias("n"), F.round(F.avg("loss1"), 6).alias("mean_loss1"), F.round(F.avg("loss2"), 6).alias("mean_loss2"))


@query("trace_calls")
def trace_calls(spark, sf):
    """Calls and tokens of the loop: 4 calls a pair at best, 16 at worst."""
    per = Chain(spark, sf).trace().groupBy("pair_id").agg(F.count("*").alias("calls"), F.sum("tokens_in").alias("tin"), F.sum("tokens_out").alias("tout"))
    return per.agg(F.count("*").alias("pairs"), F.min("calls").alias("least"), F.max("calls").alias("most"), F.round(F.avg("calls"), 6).alias("mean_calls"), F.sum("tin").alias("tokens_in"), F.sum("tout").alias("tokens_out"))


@query("chain_account", f"WITH RECURSIVE {LOW_SQL} SELECT (SELECT count(*) FROM low) AS low, true AS adds_up, true AS one_a_cluster, true AS pairs_differ")
def chain_account(spark, sf):
    """The account of the merge: intra and inter make the total, each cluster of several representatives ends with one
    row, and no pair across clusters has two rows of one cluster."""
    c = Chain(spark, sf)
    by = {r["config"]: r["n"] for r in c.merged().groupBy("config").agg(F.count("*").alias("n")).collect()}  # two rows
    several = c.reps().groupBy("cluster_id").count().where("count > 1").count()
    cluster = lambda k: c.reps().select(F.col("sample_id").cast("string").alias(k), F.col("cluster_id").alias(f"c{k}"))
    same = c.pairs().join(cluster("a"), "a").join(cluster("b"), "b").where("ca = cb").isEmpty()
    low = c.tier("low").agg(F.count("*").alias("low"))
    return low.select("low", F.lit(sum(by.values()) == c.merged().count()).alias("adds_up"), F.lit(by.get("intra", 0) == several).alias("one_a_cluster"), F.lit(same).alias("pairs_differ"))


@query("chain_yield")
def chain_yield(spark, sf):
    """Rows by configuration, and their share of the low documents."""
    c = Chain(spark, sf)
    low = c.tier("low").agg(F.count("*").alias("low"))
    return c.merged().groupingSets([["config"], []], "config").agg(F.count("*").alias("n")).crossJoin(low).select("config", "n", "low", F.round(F.col("n") / F.col("low"), 6).alias("share"))


VARIANTS = {"full": Options(), "no_cycle1": Options(cycle1=False), "no_cycle2": Options(cycle2=False), "no_strategies": Options(strategies=False), "no_purge": Options(purge=False), "one_regeneration": Options(max_regen=1), "no_regeneration": Options(max_regen=0)}


@query("fuse_ablation")
def fuse_ablation(spark, sf):
    """The loop without one of its parts at a time, on the chain's pairs: losses, calls, and rows whose answer differs
    from that of the whole loop."""
    pairs, out = Chain(spark, sf).pairs(), None
    whole = Chain(spark, sf).inter().select("pair_id", F.col("assistant").alias("full"))
    for name, options in VARIANTS.items():
        merged, trace = fuse(pairs, options)
        differs = F.count_if(F.col("assistant") != F.col("full")).alias("other_answers")
        row = merged.join(whole, "pair_id").agg(F.lit(name).alias("variant"), F.count("*").alias("pairs"), F.round(F.avg("loss1"), 6).alias("mean_loss1"), F.round(F.avg("loss2"), 6).alias("mean_loss2"), differs).crossJoin(trace.agg(F.count("*").alias("calls")))
        out = row if out is None else out.union(row)
    return out


@query("term_retention")
def term_retention(spark, sf):
    """The share of the parents' clean terms that the merged rows keep, by relation."""
    c = Chain(spark, sf)
    both = c.inter().select("pair_id", "relation", "assistant").join(prepared(c.pairs()).select("pair_id", "wanted"), "pair_id")
    kept = F.size(F.array_intersect("wanted", rules.term_set(F.col("assistant")))) / F.greatest(F.size("wanted"), F.lit(1))
    return both.withColumn("kept", kept).groupBy("relation").agg(F.count("*").alias("n"), F.round(F.avg("kept"), 6).alias("retention"))


class Merger(TextModel):
    """A stand-in for a hosted model: relates by the lengths of the texts, merges by joining them, finds nothing missing
    but in drafts whose prompt has not been patched, and now and then answers no JSON."""

    def generate(self, prompts, options):
        replies = []
        for p in prompts:
            op = p[1 : p.index("]")]
            if op == "relate":
                replies.append(["same", " Related", "nonsense"][len(p) % 3])
            elif op in ("draft", "revise"):
                replies.append(p.split("hints: ", 1)[1].split("\n", 1)[-1].replace("\n", ". "))
            else:
                replies.append("not JSON" if len(p) % 5 == 0 else '{"drop": [], "missing": []}')
        return replies


@query("fuse_model", f"WITH RECURSIVE {_LOOP} SELECT count(*) AS pairs, true AS cached, true AS all_rows, true AS bounded FROM w0")
def fuse_model(spark, sf):
    """The loop with a text model: every call is in the cache, a second run makes none, each pair gives a row, and no
    pair needs more than the most calls."""
    pairs, cache = low_pairs(spark, sf), scratch(spark, "calls")
    merged, trace = fuse(pairs, model=Merger(), cache=cache)
    first = spark.read.parquet(cache).count()
    again, _ = fuse(pairs, model=Merger(), cache=cache)
    same = again.select("pair_id", "assistant").exceptAll(merged.select("pair_id", "assistant")).isEmpty()
    most = trace.groupBy("pair_id").count().agg(F.max("count")).first()[0]
    calls, kept = trace.count(), spark.read.parquet(cache).count()
    return pairs.agg(F.count("*").alias("pairs")).select("pairs", F.lit(first == kept and first <= calls and same).alias("cached"), (F.lit(merged.count()) == F.col("pairs")).alias("all_rows"), F.lit((most or 0) <= 16).alias("bounded"))


@query("replay_hit_rate", "SELECT count(*) AS n, count(*) FILTER (WHERE doc_id % 2 = 0) AS hits, count(*) FILTER (WHERE doc_id % 2 = 1) AS misses, count(*) AS cached FROM documents")
def replay_hit_rate(spark, sf):
    """A cache that holds the calls of every second document: hits are replayed, misses are called once and kept."""
    prompts = read(spark, sf, "documents").select("doc_id", F.concat_ws("|", F.col("doc_id").cast("string"), "text").alias("prompt"))
    options, cache = {"temperature": "0.2"}, scratch(spark, "calls")
    ask(prompts.where("doc_id % 2 = 0"), EchoModel(), "draft", cache, options).count()
    hits, misses = replay(prompts, spark.read.parquet(cache), "draft", options)
    counted = [hits.count(), call(misses, EchoModel(), options).count()]
    ask(prompts, EchoModel(), "draft", cache, options).count()
    return prompts.agg(F.count("*").alias("n")).select("n", F.lit(counted[0]).cast("bigint").alias("hits"), F.lit(counted[1]).cast("bigint").alias("misses"), F.lit(spark.read.parquet(cache).count()).cast("bigint").alias("cached"))


@query("blend", f"WITH RECURSIVE {LOW_SQL} SELECT 'high' AS origin, (SELECT count(*) FROM documents) - (SELECT count(*) FROM low) AS n, true AS all_there")
def blend(spark, sf):
    """High documents and merged rows in one table, by origin; the merged ones are as many as the chain made."""
    c = Chain(spark, sf)
    by = c.blended().groupBy("origin").agg(F.count("*").alias("n"))
    made = by.where("origin = 'synthetic'").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("m")).crossJoin(c.merged().agg(F.count("*").alias("k")))
    return by.where("origin = 'high'").crossJoin(made).select("origin", "n", (F.col("m") == F.col("k")).alias("all_there"))


@query("diversity_gain")
def diversity_gain(spark, sf):
    """Word diversity of the merged rows of both configurations beside the documents they stand on."""
    c = Chain(spark, sf)
    used = c.merged().select(F.explode("leaves").alias("sample_id")).distinct()
    parents = c.low_texts().join(used, "sample_id").select("text", F.lit(0).alias("id"))
    own = c.merged().select(F.concat_ws("\n", "user", "assistant").alias("text"), F.lit(0).alias("id"))
    both = metrics.diversity(parents, "id", "text").withColumn("rows_", F.lit("parents")).union(metrics.diversity(own, "id", "text").withColumn("rows_", F.lit("merged")))
    grams = metrics.distinct_ngrams(parents, "id", "text").withColumn("rows_", F.lit("parents")).union(metrics.distinct_ngrams(own, "id", "text").withColumn("rows_", F.lit("merged")))
    return both.join(grams.select("rows_", F.col("ratio").alias("bigram_ratio")), "rows_")
