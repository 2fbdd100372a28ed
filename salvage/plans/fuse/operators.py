"""The operators that the loop calls, by rules and by a text model; each adds one column to the rows it gets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from salvage.plans.fuse import rules
from salvage.plans.fuse.backends import TextModel, ask

#: Score of a loss that could not be read: worse than any that could, so that the version is made again.
UNREADABLE = 1_000_000


class RuleOperators:
    """The operators as expressions; no calls."""

    def relate(self, df: DataFrame) -> DataFrame:
        return df.withColumn("relation", rules.relate(F.col("wa"), F.col("wb")))

    def draft(self, df: DataFrame) -> DataFrame:
        kept = df.withColumn("ca", rules.chosen(F.col("prompt"), F.col("sa"))).withColumn("cb", rules.chosen(F.col("prompt"), F.col("sb")))
        return kept.withColumn("answer", rules.arrange(F.col("prompt.base_id"), F.col("ca"), F.col("cb"))).drop("ca", "cb")

    def audit(self, df: DataFrame) -> DataFrame:
        return df.withColumn("loss", rules.audit(F.col("answer"), F.col("wanted")))

    def check(self, df: DataFrame) -> DataFrame:
        return df.withColumn("loss", rules.check_answer(F.col("question"), F.col("answer")))

    def revise(self, df: DataFrame) -> DataFrame:
        return df.withColumn("answer", rules.revise_answer(F.col("prompt"), F.col("answer"), F.col("parents")))


class ModelOperators:
    """The operators as prompts to a text model, whose calls go through the cache folder.

    Relations are asked for at temperature 0.4, all else at 0.2. An answer comes back as text, a loss as a JSON object; a
    relation that is none of the three counts as unrelated, a missing answer as an empty one, an unreadable loss as the
    worst, so that the row is made again as long as regenerations are left.
    """

    def __init__(self, model: TextModel, cache: str):
        self.model, self.cache = model, cache

    def _ask(self, df: DataFrame, op: str, task: str, *parts: Column, temperature: str = "0.2") -> DataFrame:
        prompt = F.concat_ws("\n", F.lit(f"[{op}] {task}"), *parts)
        return ask(df.withColumn("_prompt", prompt), self.model, op, self.cache, {"temperature": temperature}, "_prompt").drop("_prompt")

    def _loss(self, df: DataFrame) -> DataFrame:
        read = F.from_json("reply", "drop array<string>, missing array<string>, keep array<string>")
        none = F.array().cast("array<string>")
        part = lambda name: F.coalesce(read[name], none)
        fine = read["drop"].isNotNull() & read["missing"].isNotNull()
        score = F.when(fine, F.size(part("drop")) + F.size(part("missing"))).otherwise(UNREADABLE)
        loss = F.struct(part("keep").alias("keep"), part("drop").alias("drop"), part("missing").alias("missing"), score.alias("score"))
        return df.withColumn("loss", loss).drop("reply")

    def _text(self, df: DataFrame) -> DataFrame:
        return df.withColumn("answer", rules.sentences(F.coalesce("reply", F.lit("")))).drop("reply")

    def _wishes(self) -> Column:
        p = F.col("prompt")
        line = lambda name, values: F.concat(F.lit(f"{name}: "), F.array_join(values, ", "))
        return F.concat_ws("\n", line("strategy", F.array(p["base_id"])), line("keep", p["must_keep"]), line("drop", p["must_drop"]), line("hints", p["hints"]))

    def relate(self, df: DataFrame) -> DataFrame:
        said = self._ask(df, "relate", "Answer same, related or unrelated.", F.array_join("sa", ". "), F.array_join("sb", ". "), temperature="0.4")
        word = F.lower(F.trim("reply"))
        return said.withColumn("relation", F.when(word.isin("same", "related"), word).otherwise("unrelated")).drop("reply")

    def draft(self, df: DataFrame) -> DataFrame:
        return self._text(self._ask(df, "draft", "Merge the two texts.", self._wishes(), F.array_join("sa", ". "), F.array_join("sb", ". ")))

    def audit(self, df: DataFrame) -> DataFrame:
        return self._loss(self._ask(df, "audit", "Which of the terms are missing, which sentences are to drop? JSON.", F.array_join("wanted", ", "), F.array_join("answer", ". ")))

    def check(self, df: DataFrame) -> DataFrame:
        return self._loss(self._ask(df, "check", "What does the answer lack, which sentences are to drop? JSON.", F.col("question"), F.array_join("answer", ". ")))

    def revise(self, df: DataFrame) -> DataFrame:
        return self._text(self._ask(df, "revise", "Revise the answer.", self._wishes(), F.array_join("answer", ". "), F.array_join("parents", ". ")))
