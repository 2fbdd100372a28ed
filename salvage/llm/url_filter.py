"""URL verdicts by pattern rules that are indexed by their rarest literal token.

Each rule lists literal tokens that any url it fits must contain. The tokens' frequencies over the whole url column
choose the rarest one, under which the rule is filed. The tokens of a url fetch the few rules filed under them by hash,
and only those run their regular expression. All of it is built-in expressions. A rule list of ordinary size is a hash
table inside the plan, so urls take part in no join and no exchange; a longer one is a table that tokens are joined to.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import asdict, dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.llm.common import checkpoint

#: Rules up to which the index is a constant of the plan (some hundred KB), and rows up to which a side is broadcast.
PLAN_RULES, BROADCAST_ROWS = 5_000, 500_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_AUTHORITY = r"(?s)^.*?://([^/?#]*)"
_PATH = r"(?s)^.*?://[^/?#]*([^?#]*)"


@dataclass(frozen=True)
class UrlRule:
    """``tokens``: words that every fitting url holds. ``rank``: the highest fitting rank decides."""

    name: str
    action: str
    pattern: str
    tokens: tuple[str, ...]
    rank: int
    listed: bool = False


def host_rule(action: str, host: str, path: str) -> UrlRule:
    """A listed rule: its host and subdomains, and a path that starts with ``path``; longer rules win."""
    whole = [t for t in re.split(r"[^a-z0-9]+", host) if t] + re.findall(r"(?<=/)[A-Za-z0-9]+(?=/)", path)
    return UrlRule(host + path, action, rf"^(?:[^/]*\.)?{re.escape(host)}{re.escape(path)}", tuple(t.lower() for t in whole), 1000 + len(host + path), True)


def word_rules() -> list[UrlRule]:
    """The method's own rules, some hundreds: hosts and paths that hold a topic word, topic words beside a word of
    solicitation, and paths of logins, trackers and programs. A rule of two words outranks one of a single word."""
    # Topic words, words of solicitation beside them, path words and file endings, in order.
    topics = "casino bets betting poker slots roulette jackpot lottery bingo porn xxx adult escort sexcam hentai viagra cialis pills pharmacy steroids payday loans forex binary malware phishing warez torrent cracks keygen serials nulled doubleclick adserver adservice tracker clickbank popads replica".split()
    beside = "free online best top cheap live real hot play win buy click".split()
    path_words = "wp-login wp-admin xmlrpc phpmyadmin cgi-bin affiliate clickthrough popunder".split()
    edge, end = "(?:^|[^a-z0-9])", "(?:[^a-z0-9]|$)"
    rules = [UrlRule(f"host:{w}", "block", rf"^(?:[^/]*[^a-z0-9/])?{w}(?:[^a-z0-9/][^/]*)?(?:/|$)", (w,), 10) for w in topics]
    rules += [UrlRule(f"pair:{b}-{w}", "block", rf"{edge}(?:{b}[^a-z0-9]+{w}|{w}[^a-z0-9]+{b}){end}", (b, w), 8) for w in topics for b in beside]
    rules += [UrlRule(f"path:{w}", "block", rf"^[^/]*/(?:.*[/.])?{re.escape(w)}(?:[/.]|$)", tuple(w.split("-")), 5) for w in [*path_words, *topics]]
    rules += [UrlRule(f"file:{e}", "block", rf"\.{e}$", (e,), 5) for e in "exe msi apk dmg scr".split()]
    return rules


#: The rules of the contract, then the method's.
RULES = [host_rule("allow", "org", "/"), host_rule("block", "example.org", "/es/"), host_rule("block", "example.org", "/en/1"), host_rule("allow", "com", "/fr/"), host_rule("block", "com", "/de/"), *word_rules()]


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, _AUTHORITY, 1), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _PATH, 1), F.lit(""))


def _tokens(address: Column) -> Column:
    return F.array_distinct(F.split(F.translate(address, _UPPER, _LOWER), r"[^a-z0-9]+"))


_RULE = "struct<rank:int,name:string,action:string,listed:boolean,pattern:string>"


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def filed_rules(addresses: DataFrame, rules: list[UrlRule]) -> tuple[DataFrame, int]:
    """(token, rule), a row a rule under its rarest token over all addresses (``address``), and the number of rules.

    Tokens of addresses meet the rules' tokens by a hash join; a rule without tokens can't be filed.
    """
    assert all(r.tokens for r in rules)
    spark = addresses.sparkSession
    fields = ("rank", "name", "action", "listed", "pattern")
    rows = [(i, sorted(set(r.tokens)), tuple(asdict(r)[f] for f in fields)) for i, r in enumerate(rules)]
    table = spark.createDataFrame(rows, f"i int, tokens array<string>, rule {_RULE}")
    wanted = table.select("i", "rule", F.explode("tokens").alias("token"))
    names = _small(wanted.select("token").distinct(), len(rules))
    counts = addresses.select(F.explode(_tokens(F.col("address"))).alias("token")).join(names, "token", "left_semi").groupBy("token").agg(F.count("*").alias("n"))
    known = wanted.join(counts, "token", "left").select("i", "rule", F.struct(F.coalesce("n", F.lit(0)).alias("n"), "token").alias("t"))
    return known.groupBy("i").agg(F.min("t").alias("t"), F.first("rule").alias("rule")).select("t.token", "rule"), len(rules)


def _in_plan(index: DataFrame) -> Column:
    """The index as a constant: slots by the token's crc32, each with its (token, rules); a lookup reads one slot."""
    by: dict[str, list] = {}
    for r in index.collect():
        by.setdefault(r["token"], []).append(r["rule"].asDict())
    slots = 1 << (2 * len(by)).bit_length()
    table: list[list] = [[] for _ in range(slots)]
    for token in sorted(by):
        table[zlib.crc32(token.encode()) % slots].append({"t": token, "rules": by[token]})
    text = lambda x: "'" + x.replace("\\", "\\\\").replace("'", "\\'") + "'"
    rule = lambda r: f"named_struct('rank', {r['rank']}, 'name', {text(r['name'])}, 'action', {text(r['action'])}, 'listed', {str(r['listed']).lower()}, 'pattern', {text(r['pattern'])})"
    one = lambda x: f"named_struct('t', {text(x['t'])}, 'rules', array({', '.join(map(rule, x['rules']))}))"
    empty = f"cast(array() as array<struct<t:string,rules:array<{_RULE}>>>)"
    slots_ = ", ".join(f"array({', '.join(map(one, slot))})" if slot else empty for slot in table)
    filed = F.expr(f"array({slots_})")  # folded to one constant; a parsed JSON text would be read for every url

    def fetch(token: Column) -> Column:
        slot = F.element_at(filed, (F.pmod(F.crc32(token), F.lit(slots)) + 1).cast("int"))
        return F.flatten(F.transform(F.filter(slot, lambda x: x["t"] == token), lambda x: x["rules"]))

    return F.flatten(F.transform(_tokens(F.concat("host", "path")), fetch))


def judge_urls(df: DataFrame, url_col: str = "url", rules: list[UrlRule] | None = None, default: str = "allow", plan_rules: int = PLAN_RULES) -> DataFrame:
    """``df`` with host, path, rule, verdict and pattern_rule (the method's rule that decided, else null).

    A null url or one without ``://`` has an empty host and path, fits no rule and gets ``default``; repeated rows are
    judged alike; of fitting rules the highest rank decides, ties by name; an empty table gives an empty result. Columns
    of ``df`` with the added names are replaced. More than ``plan_rules`` rules are joined by token; that list is
    broadcast only up to BROADCAST_ROWS rows. Both ways give the same rows.
    """
    rules = RULES if rules is None else rules
    kept = [c for c in df.columns if c not in ("host", "path", "rule", "verdict", "pattern_rule")]
    parted = df.select(*(f"`{c}`" for c in kept), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    address = F.concat("host", "path")
    fits = lambda r: F.regexp_like(address, r["pattern"])
    if not rules:
        return parted.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default), "pattern_rule": F.lit(None).cast("string")})
    if len(rules) <= plan_rules:
        index, _ = filed_rules(parted.select(address.alias("address")), rules)
        judged = parted.withColumn("_best", F.array_max(F.filter(_in_plan(index), fits)))
    else:
        numbered = checkpoint(parted.withColumn("_n", F.monotonically_increasing_id()))
        index, n = filed_rules(numbered.select(address.alias("address")), rules)
        met = numbered.select("_n", "host", "path", F.explode(_tokens(address)).alias("token")).join(_small(index, n), "token").where(fits(F.col("rule")))
        judged = numbered.join(met.groupBy("_n").agg(F.max("rule").alias("_best")), "_n", "left")
    return judged.select(
        *(f"`{c}`" for c in kept), "host", "path",
        F.when(F.col("_best.listed"), F.col("_best.name")).alias("rule"),
        F.coalesce(F.col("_best.action"), F.lit(default)).alias("verdict"),
        F.when(~F.col("_best.listed"), F.col("_best.name")).alias("pattern_rule"),
    )


def judge_sql(rules: list[UrlRule] | None = None, default: str = "allow") -> str:
    """DuckDB SQL that tries every rule on every page."""
    rules = RULES if rules is None else rules
    text = lambda s: "'" + s.replace("'", "''") + "'"
    listed = ", ".join(f"({r.rank}, {text(r.name)}, {text(r.action)}, {str(r.listed).lower()}, {text(r.pattern)})" for r in rules)
    return f"""
WITH parted AS (
  SELECT row_number() OVER () AS n, page_id,
         coalesce(translate(regexp_extract(url, '{_AUTHORITY}', 1), '{_UPPER}', '{_LOWER}'), '') AS host,
         coalesce(regexp_extract(url, '{_PATH}', 1), '') AS path FROM pages),
rules(rank, name, action, listed, pattern) AS (VALUES {listed}),
fits AS (SELECT p.n, max(struct_pack(rank := r.rank, name := r.name, action := r.action, listed := r.listed)) AS best
         FROM parted p JOIN rules r ON regexp_matches(p.host || p.path, r.pattern) GROUP BY p.n)
SELECT page_id, host, path, CASE WHEN best.listed THEN best.name END AS rule, coalesce(best.action, '{default}') AS verdict,
       CASE WHEN NOT best.listed THEN best.name END AS pattern_rule
FROM parted LEFT JOIN fits USING (n)"""
