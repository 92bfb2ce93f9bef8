"""The data model: a graph is a set of labelled edges (s, p, o) over strings."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRIPLE = "s string, p string, o string"


def validate_triples(df: DataFrame) -> DataFrame:
    """(s, p, o) as strings, without nulls."""
    missing = {"s", "p", "o"} - set(df.columns)
    if missing:
        raise ValueError(f"not a triple table, it lacks {sorted(missing)}")
    return df.select(*[F.col(c).cast("string").alias(c) for c in "spo"]).dropna()


@dataclass
class Graph:
    """``edges`` must be free of duplicates; use :meth:`of` for tables that may not be."""

    edges: DataFrame
    _names: list[str] | None = field(default=None, repr=False)
    _nodes: DataFrame | None = field(default=None, repr=False)
    _counts: dict[str, int] | None = field(default=None, repr=False)
    #: The edges lie in a folder per label, so reading those of a few labels is cheap.
    is_stored: bool = False
    #: The graph as one shard of the index, once it was asked for.
    _shard: object = field(default=None, repr=False)

    @classmethod
    def of(cls, df: DataFrame) -> Graph:
        return cls(validate_triples(df).distinct())

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def nodes(self) -> DataFrame:
        if self._nodes is not None:
            return self._nodes
        return self.edges.select(F.col("s").alias("node")).union(self.edges.select("o")).distinct()

    def labels(self) -> list[str]:
        """Label names; a table of labels is small (the largest published graphs have thousands)."""
        if self._names is None:
            self._names = sorted(r.p for r in self.edges.select("p").distinct().collect())
        return self._names

    def counts(self, names=None) -> dict[str, int]:
        """Edges of each label, or of the named ones only."""
        if self._counts is not None:
            return self._counts
        edges = self.edges if names is None else self.edges.filter(F.col("p").isin(list(names)))
        found = {r.p: r.n for r in edges.groupBy("p").agg(F.count("*").alias("n")).collect()}
        if names is None:
            self._counts = found
        return found

    def stored(self, name: str = "graph") -> Graph:
        """The graph written once: edges in a folder per label, so that a query's labels are
        pruned by folder, the node table, and the label counts."""
        from ..exec.store import Store

        store = Store(self.spark, f"graph_{name}")
        self.edges.hint("rebalance", "p").write.partitionBy("p").parquet(store.path("edges"))
        edges = self.spark.read.schema("s string, o string, p string").parquet(store.path("edges")).select("s", "p", "o")
        nodes = store.save(Graph(edges).nodes(), "nodes")
        counts = Graph(edges).counts()
        return Graph(edges, sorted(counts), nodes, counts, True)

    def completed(self) -> DataFrame:
        """Edges and their inverses, labels of inverses written ^p."""
        back = self.edges.select(F.col("o").alias("s"), F.concat(F.lit("^"), "p").alias("p"), F.col("s").alias("o"))
        return self.edges.unionByName(back)

    def path(self, text: str):
        from ..exec.planner import Fluent

        return Fluent(self, text)
