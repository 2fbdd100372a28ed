"""The whole way from ratings to merged rows, one written table a step; every step reads the step before.

Ratings are planted noise on the rubric's grades, which are the truth that only measures look at. They are corrected
with the estimated T and p; the corrected score splits the documents; the low ones are clustered, split into cells and
reduced to representatives; these are merged inside and across clusters; merged and high rows are blended.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from salvage.functions.stages import Stages
from salvage.functions.together import together
from salvage.plans import clusters, correction, fixtures, pairing, representatives, samples
from salvage.plans.fixtures import K
from salvage.plans.fuse.loop import fuse, fuse_clusters
from salvage.registry import read


class Chain:
    def __init__(self, spark: SparkSession, sf: str):
        self.spark, self.sf, self.stages = spark, sf, Stages(spark, sf)

    def _step(self, name: str, build) -> DataFrame:
        return self.stages.table(f"chain-{name}", build)

    def transition(self) -> DataFrame:
        """(i, j, prob, prior, residual): T and p as estimated from the counts of rating triples."""

        def build() -> DataFrame:
            found = correction.estimate_transition(fixtures.text_triples(self.spark, self.sf), K, "likelihood", steps=fixtures.STEPS)
            rows = [(i, j, float(found.t[i, j]), float(found.p[i]), float(found.residual)) for i in range(K) for j in range(K)]
            return self.spark.createDataFrame(rows, "i int, j int, prob double, prior double, residual double")

        return self._step("transition", build)

    def scored(self) -> DataFrame:
        """(sample_id, component, y, y1, corrected, tier, ...): every rated document; those without a corrected score are
        unassigned, as are documents that the neighbours leave out."""

        def build() -> DataFrame:
            rows = self.transition().collect()  # K * K
            t, p = correction.np.zeros((K, K)), correction.np.zeros(K)
            for r in rows:
                t[r["i"], r["j"]], p[r["i"]] = r["prob"], r["prior"]
            rated = fixtures.ratings6(self.spark, self.sf).select("sample_id", "component", "y", F.col("raw_score").alias("y1"))
            near = fixtures.text_triples(self.spark, self.sf).select("sample_id", "y2", "y3")
            fixed = correction.correct(rated.join(near, "sample_id", "left"), t, p)
            return correction.partition_by_score(fixed)

        return self._step("scored", build)

    def tier(self, name: str) -> DataFrame:
        return self.scored().where(F.col("tier") == name)

    def low_documents(self) -> DataFrame:
        """Documents of the low tier, with their columns and raw_score, corrected and y."""

        def build() -> DataFrame:
            low = self.tier("low").select(F.col("sample_id").alias("doc_id"), F.col("y1").alias("raw_score"), "corrected", "y")
            return read(self.spark, self.sf, "documents").join(low, "doc_id")

        return self._step("low-documents", build)

    def low_texts(self) -> DataFrame:
        """(sample_id, text): low documents without boilerplate and repeated lines."""

        def build() -> DataFrame:
            low = self.low_documents().drop("raw_score", "corrected", "y")
            return samples.purge_lines(low).select(F.col("id").alias("sample_id"), "text")

        return self._step("low-texts", build)

    def low_vectors(self) -> DataFrame:
        return fixtures.text_vectors(self.spark, self.sf).join(self.tier("low").select("sample_id"), "sample_id", "left_semi")

    def hops(self) -> DataFrame:
        return self._step("hops", lambda: clusters.one_hop_of_copies(self.low_vectors(), whole_rows=clusters.WHOLE_ROWS))

    def cells(self) -> DataFrame:
        return self._step("cells", lambda: clusters.subcluster(self.hops(), self.low_vectors()))

    def reps(self) -> DataFrame:
        cells = lambda: self.cells().select("sample_id", "cluster_id", "sub_id")
        return self._step("reps", lambda: representatives.choose(cells(), self.low_vectors()))

    def pairs(self) -> DataFrame:
        """Ring pairs of representatives of different clusters, with their texts."""

        def build() -> DataFrame:
            return with_texts(pairing.inter_pairs(self.reps()), self.low_texts())

        return self._step("pairs", build)

    def _merge_across(self, name: str) -> DataFrame:
        keys = [("merged", 0), ("trace", 1)]
        if any((*self.stages.key, f"chain-inter-{k}") not in _known() for k, _ in keys):
            both = fuse(self.pairs())
            for k, i in keys:
                self._step(f"inter-{k}", lambda i=i: both[i])
        return self._step(f"inter-{name}", lambda: None)

    def inter(self) -> DataFrame:
        return self._merge_across("merged")

    def trace(self) -> DataFrame:
        return self._merge_across("trace")

    def intra(self) -> DataFrame:
        """All merges inside clusters, with the documents they stand on and their round."""
        return self._step("intra", lambda: fuse_clusters(self.reps(), self.low_texts())[1])

    def merged(self) -> DataFrame:
        """(merged_id, config, leaves, user, assistant, status): merged rows of both configurations. Inside a cluster only
        the last merge is a row of the result; those before are parts of it."""

        def build() -> DataFrame:
            across, inside = together(self.inter, self.intra)
            across = across.select("merged_id", F.lit("inter").alias("config"), F.transform("parents", lambda x: x.cast("bigint")).alias("leaves"), "user", "assistant", "status")
            last = inside.groupBy("cluster_id").agg(F.max("round").alias("round"))
            final = inside.join(last, ["cluster_id", "round"]).select("merged_id", F.lit("intra").alias("config"), "leaves", "user", "assistant", "status")
            return across.union(final)

        return self._step("merged", build)

    def blended(self) -> DataFrame:
        """High documents and merged rows in one table."""
        high = read(self.spark, self.sf, "documents").join(self.tier("high").select(F.col("sample_id").alias("doc_id")), "doc_id", "left_semi")
        return pairing.blend(high.select(F.col("doc_id").cast("string").alias("id"), "text"), self.merged().select(F.col("merged_id").alias("id"), F.concat_ws("\n", "user", "assistant").alias("text")))


def low_documents(spark: SparkSession, sf: str) -> DataFrame:
    """Documents of the low tier, with their columns and raw_score, corrected and y."""
    return Chain(spark, sf).low_documents()


def _known() -> dict:
    from salvage.functions import stages

    return stages._WRITTEN


def with_texts(found: DataFrame, texts: DataFrame) -> DataFrame:
    """``found`` (a, b) as pairs for the loop."""
    own = texts.select(F.col("sample_id").alias("i"), "text")
    with_a = found.join(own.withColumnsRenamed({"i": "a", "text": "text_a"}), "a")
    both = with_a.join(own.withColumnsRenamed({"i": "b", "text": "text_b"}), "b")
    return both.select(F.concat_ws("-", "a", "b").alias("pair_id"), F.col("a").cast("string").alias("a"), F.col("b").cast("string").alias("b"), "text_a", "text_b")
