"""Choice of execution and the fluent surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.register import register
from ..operators import measures, rouge, runs
from ..operators.backbones import Backbone, LeadBackbone
from ..schema import check_utterances, positive

SMALL_BYTES = 8 << 20


def execution(backbone: Backbone, batched: bool = False, snippets: bool = True) -> str:
    """frontier for generators that serve large batches, jump for the lead backbone when only boundaries are asked, else map-local."""
    if batched:
        return "frontier"
    return "jump" if isinstance(backbone, LeadBackbone) and not snippets else "map"


def small(df: DataFrame, most_bytes: int = SMALL_BYTES) -> DataFrame:
    """df with a broadcast hint if the optimizer's size estimate allows it, else as it is."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(df) if size <= most_bytes else df


def persist(df: DataFrame, key: str = "meeting_id", partitions: int | None = None) -> DataFrame:
    """Co-located by meeting and kept for reuse by several passes."""
    return (df.repartition(partitions, key) if partitions else df.repartition(key)).persist()


class Digest:
    """Digest(spark).meetings(df).windows(k=1024).backbone(G).run().dedup().score(ref)"""

    def __init__(self, spark: SparkSession):
        self.spark, self.utts, self.k, self.resume, self.stop, self.generator, self.steps_, self.outputs_ = spark, None, 1024, "after", "boundary", LeadBackbone(), None, None
        register(spark)

    def meetings(self, utts: DataFrame, check: bool = False) -> Digest:
        self.utts = check_utterances(utts) if check else utts
        return self

    def windows(self, k: int = 1024) -> Digest:
        positive(k=k)
        self.k = k
        return self

    def stride(self, kind: str = "last_support", resume: str = "after", stop: str = "boundary") -> Digest:
        if kind not in ("last_support", "fixed", "truncate"):
            raise ValueError(f"kind must be last_support, fixed or truncate, not {kind}")
        self.kind, self.resume, self.stop = kind, resume, stop
        return self

    def backbone(self, generator: Backbone) -> Digest:
        self.generator = generator
        return self

    def run(self) -> Digest:
        if self.utts is None:
            raise ValueError("no meetings given")
        kind = getattr(self, "kind", "last_support")
        if kind == "fixed":
            self.steps_ = runs.fixed_run(self.utts, self.generator, self.k)
        elif kind == "truncate":
            self.steps_ = runs.truncate_run(self.utts, self.generator, self.k)
        else:
            self.steps_ = runs.dynamic(self.utts, self.generator, self.k, self.resume, self.stop)
        self.outputs_ = runs.assemble(self.steps_)
        return self

    def dedup(self) -> Digest:
        self.outputs_ = runs.dedup_sentences(self.outputs_).select("meeting_id", "text")
        return self

    def steps(self) -> DataFrame:
        return self.steps_

    def outputs(self) -> DataFrame:
        return self.outputs_

    def cost(self) -> DataFrame:
        return measures.cost(self.steps_)

    def score(self, references: DataFrame) -> DataFrame:
        """(measure, n, p, r, f) of ROUGE-1, -2 and -L."""
        pairs = rouge.pairs(self.outputs_, references)
        return rouge.means(rouge.ngram_by_row(pairs, 1), "r1").unionByName(rouge.means(rouge.ngram_by_row(pairs, 2), "r2")).unionByName(rouge.means(rouge.longest(pairs), "rl"))
