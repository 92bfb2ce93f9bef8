"""Incremental answers for edges that only arrive, one target fixed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks
from ..exec import backward, state
from ..exec.options import RpqOptions
from ..exec.store import Store
from ..graph.model import Graph
from ..lang.parser import parse


class Incremental:
    """Keeps the visited masks of (x, path, o) and extends them with each batch of edges.

    New edges are stepped over once from the masks of their ends; what is new goes on
    as a frontier over all edges. Deletions are not supported.
    """

    def __init__(self, g: Graph, path: str, o: str):
        self.spark, self.tables = g.spark, bitparallel.compile(parse(path))
        self.masks, self.store, self.k, self.o = Masks(self.tables), Store(g.spark, "incremental"), 0, o
        self.edges = self.store.save(g.edges, "edges/0")
        self._seed = self.spark.createDataFrame([(o, self.masks.value(self.tables.nfa.mask(self.tables.nfa.last)))], f"node string, mask {self.masks.type}")
        self._run(self._seed)

    def _run(self, seeds: DataFrame) -> None:
        seen = backward.traverse(self._graph(), self.tables, seeds, [], True, RpqOptions())
        self.visited = self.store.save(state.merged(seen, self.masks, []), f"visited/{self.k}")

    def _graph(self) -> Graph:
        # Written already, so a traversal reads the edges where they lie and copies none.
        return Graph(self.edges, is_stored=True)

    def add(self, edges: DataFrame) -> None:
        self.k += 1
        new = edges.select("s", "p", "o").distinct().join(self.edges, ["s", "p", "o"], "left_anti")
        new = self.store.save(new, f"edges/{self.k}")
        self.edges = self.store.rounds(new.schema, "edges")
        steps = state.moves(Graph(new), self.masks, True)
        first = state.fresh(state.step(self.visited, steps, self.masks, [], True), self.visited, self.masks, [])
        # What was visited before takes part as seeds, so the traversal only adds to it.
        old = self.visited
        front = self.store.save(first, f"front/{self.k}")
        masks = self.masks
        if front.limit(1).count():
            seen = backward.traverse(self._graph(), self.tables, front, [], True, RpqOptions(), premarked=old)
            self.visited = self.store.save(state.merged(seen.unionByName(old), masks, []), f"visited/{self.k}")

    def answers(self) -> DataFrame:
        m = self.masks
        out = self.visited.filter(m.some(m.both(F.col("mask"), m.lit(self.tables.initial)))).select(F.col("node").alias("s"))
        if self.tables.nfa.nullable:
            out = out.union(Graph(self.edges).nodes().filter(F.col("node") == self.o).select(F.col("node").alias("s"))).distinct()
        return out

    def start(self, stream: DataFrame, checkpoint: str):
        """Attaches to a stream of edges (s, p, o)."""
        return stream.writeStream.foreachBatch(lambda df, _: self.add(df)).option("checkpointLocation", checkpoint).start()
