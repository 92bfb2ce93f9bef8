"""Search of the product of graph and automaton with one row per (node, state)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import epsilon, position, subset
from ..exec.store import Store
from ..graph.model import Graph
from ..lang.ast import Expr
from ..lang.parser import parse
from ..lang.rewrite import reverse


def transitions(g: Graph, e: Expr, automaton: str = "position") -> tuple[list[tuple], int, set[int]]:
    """(from, label, inverse, to) rows, the start state and the final states."""
    names = g.labels()
    if automaton == "position":
        nfa = position.build(e)
        rows = [(q, n, i, t) for q in range(nfa.m + 1) for t in nfa.after(q) for n, i in nfa.positions[t - 1].over(names)]
        return rows, 0, nfa.last | ({0} if nfa.nullable else set())
    nfa = epsilon.build(e)
    nfa = subset.build(nfa, names) if automaton == "subset" else nfa.without_empty()
    return [(a, n, i, b) for a, c, b in nfa.moves for n, i in c.over(names)], nfa.start, nfa.finals


def materialise(g: Graph, e: Expr | str, automaton: str = "position") -> DataFrame:
    """The whole product graph: (node, state, to, to_state)."""
    e = parse(e) if isinstance(e, str) else e
    rows, _, _ = transitions(g, e, automaton)
    t = F.broadcast(g.spark.createDataFrame(rows, "q int, p string, inverse boolean, r int"))
    moved = g.edges.join(t, "p")
    at, to = F.when(F.col("inverse"), F.col("o")).otherwise(F.col("s")), F.when(F.col("inverse"), F.col("s")).otherwise(F.col("o"))
    return moved.select(at.alias("node"), F.col("q").alias("state"), to.alias("to"), F.col("r").alias("to_state")).distinct()


def turned(steps: DataFrame) -> DataFrame:
    """The product graph with its steps turned round."""
    return steps.select(F.col("to").alias("node"), F.col("to_state").alias("state"), F.col("node").alias("to"), F.col("state").alias("to_state"))


def reached(g: Graph, e: Expr | str, sources: DataFrame | None = None, automaton: str = "position", whole: bool = False, backward: bool = False) -> tuple[DataFrame, set[int], int]:
    """(origin, node, state) of all product nodes reached from sources; finals; rounds.

    ``backward``: against the steps of the same automaton, from the sources in its final states.
    """
    e = parse(e) if isinstance(e, str) else e
    _, start, finals = transitions(g, e, automaton)
    store = Store(g.spark, "product")
    steps = materialise(g, e, automaton)
    if backward:
        steps = turned(steps)
    steps = store.save(steps, "steps") if whole else steps
    nodes = (sources if sources is not None else g.nodes()).join(g.nodes(), "node", "left_semi")
    front = store.save(nodes.select(F.col("node").alias("origin"), "node", F.explode(F.array(*[F.lit(q) for q in (sorted(finals) if backward else [start])])).alias("state")), "rounds/0")
    k = 0
    while front.limit(1).count():
        k += 1
        seen = store.rounds(front.schema, "rounds")
        new = front.join(steps, ["node", "state"]).select("origin", F.col("to").alias("node"), F.col("to_state").alias("state")).distinct()
        front = store.save(new.join(seen, ["origin", "node", "state"], "left_anti"), f"rounds/{k}")
    return store.rounds(front.schema, "rounds"), finals, k


def evaluate(g: Graph, e: Expr | str, s: str | None = None, o: str | None = None, automaton: str = "position", materialised: bool = False) -> DataFrame:
    """(s, o) pairs; ``materialised`` writes the product graph before the search."""
    e = parse(e) if isinstance(e, str) else e
    if s is None and o is not None:
        # From the constant end, over the mirrored expression.
        out = evaluate(g, reverse(e), o, None, automaton, materialised)
        return out.select(F.col("o").alias("s"), F.col("s").alias("o"))
    sources = g.spark.createDataFrame([(s,)], "node string") if s is not None else None
    seen, finals, _ = reached(g, e, sources, automaton, materialised)
    out = seen.filter(F.col("state").isin(*finals)).select(F.col("origin").alias("s"), F.col("node").alias("o")).distinct()
    return out.filter(F.col("o") == o) if o is not None else out
