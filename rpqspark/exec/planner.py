"""From a query (s, path, o) to a plan and its answers.

Answers are a set: one column per variable, names decoded; with two constants one
row (found). Empty paths relate nodes of the graph to themselves.
"""

from __future__ import annotations

import dataclasses
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks
from ..graph.model import Graph
from ..lang import patterns, rewrite
from ..lang.ast import At, Cat, Class, Expr, text
from ..lang.parser import parse
from . import backward, fastpaths, kernel, pairs, rare, ring
from .options import RpqOptions, RunStats


@dataclass
class RpqPlan:
    expr: Expr
    s: str | None
    o: str | None
    same: bool
    pattern: str
    fast_path: str
    start: str
    executor: str
    labels: list[str]
    reason: str = ""

    def explain(self) -> str:
        lines = [f"pattern   {self.pattern}", f"path      {text(self.expr)}", f"ends      s={self.s or 'variable'}, o={self.o or 'variable'}" + (", the same variable" if self.same else "")]
        lines += [f"strategy  joins ({self.fast_path})" if self.fast_path else f"strategy  {self.executor}, starting at {self.start}" + (f" ({self.reason})" if self.reason else "")]
        return "\n".join([*lines, f"labels    {', '.join(self.labels) or 'none'}"])


def choose_direction(e: Expr, counts: dict[str, int]) -> tuple[str, str]:
    """For two open ends: start at the end whose first labels have fewer edges.

    A path that begins with one plain step before a closure starts there in any case.
    """
    nfa = bitparallel.compile(e).nfa
    size = lambda states: sum(counts.get(n, 0) for q in states for n, _ in nfa.positions[q - 1].labels)
    if isinstance(e, Cat) and len(e.parts) == 2 and fastpaths.plan(e.parts[0]) == "single" and not fastpaths.plan(e.parts[1]):
        return "subjects", "the path begins with one plain step"
    a, b = size(nfa.first), size(nfa.last)
    return ("subjects", f"{a} edges against {b}") if a <= b else ("objects", f"{b} edges against {a}")


def _plain(parts) -> list[str]:
    return [next(iter(p.labels))[0] for p in parts if isinstance(p, Class) and not p.negated and len(p.labels) == 1 and not next(iter(p.labels))[1]]


def rare_label(e: Expr, counts: dict[str, int], times: int) -> str | None:
    """The label of a top-level concatenation at which to split a query with two open ends: it
    stands there once, forward, and has ``times`` fewer edges than either end would start with."""
    plain = _plain(e.parts if isinstance(e, Cat) else ())
    nfa = bitparallel.compile(e).nfa
    ends = min(sum(counts.get(n, 0) for q in states for n, _ in nfa.positions[q - 1].labels) for states in (nfa.first, nfa.last)) if nfa.positions else 0
    rare = [x for x in plain if plain.count(x) == 1 and counts.get(x, 0) * times <= ends]
    return min(rare, key=lambda x: (counts.get(x, 0), x)) if rare else None


def inner_label(e: Expr, counts: dict[str, int]) -> str | None:
    """The label with the fewest edges that stands once, forward, in a top-level concatenation, but not at an end of it."""
    parts = e.parts if isinstance(e, Cat) else ()
    plain = _plain(parts)
    return min((x for x in _plain(parts[1:-1]) if plain.count(x) == 1), key=lambda x: (counts.get(x, 0), x), default=None)


def _constant(term: str | None) -> str | None:
    return None if patterns.is_variable(term) else term


def plan(g: Graph, path: str | Expr, s: str | None = None, o: str | None = None, options: RpqOptions = RpqOptions()) -> RpqPlan:
    """``s`` and ``o``: a node's name, or None or ?name for a variable."""
    e = rewrite.simplify(rewrite.push_inverse(parse(path) if isinstance(path, str) else path))
    same = s is not None and s == o and patterns.is_variable(s)
    cs, co = _constant(s), _constant(o)
    fast = fastpaths.plan(e) if options.fast_paths and options.executor in ("auto", "joins") else ""
    start, reason = "o" if co is not None else "s" if cs is not None else options.order, ""
    if cs is not None and co is not None and options.direction == "forward":
        start = "s"
    names = sorted({n for c in rewrite.symbols(e) for n, _ in c.over(g.labels() if c.negated else [])})
    if options.direction == "auto" and not fast:
        if cs is None and co is None:
            start, reason = choose_direction(e, g.counts(names))
        elif cs is not None and co is not None:
            side, reason = choose_direction(e, g.counts(names))
            start = "s" if side == "subjects" else "o"
    return RpqPlan(e, cs, co, same, patterns.classify(s, e, o), fast, start, options.executor, names, reason)


def evaluate(g: Graph, path: str | Expr, s: str | None = None, o: str | None = None, options: RpqOptions = RpqOptions(), s_set: DataFrame | None = None, o_set: DataFrame | None = None, stats: RunStats | None = None, node_filter: dict[int, DataFrame] | None = None) -> DataFrame:
    """Answers of a path query.

    ``s_set``, ``o_set``: (node), several start or end nodes in place of a constant; the answers
    are the other ends that reach, or are reached from, some of them, and a constant or a set at
    that other end keeps only its own members (with two sets: the starts). ``node_filter``:
    by position of the expression (from 1), the nodes at which it may be entered.
    """
    stats = stats if stats is not None else RunStats()
    if options.executor == "ring" and not options.index_only and not ring.fits(g, options.kernel_edges):
        # Beyond one shard the planner picks, star-free paths by joins.
        options = dataclasses.replace(options, executor="auto", fast_paths=True)
        stats.extra["index"] = "the graph is over one shard"
    p = plan(g, path, s, o, options)
    tables = bitparallel.compile(p.expr, options.chunk_bits, options.mask_bits)
    stats.labels_read, stats.labels_pruned = len(p.labels), max(0, len(g._names or []) - len(p.labels))
    if s_set is not None or o_set is not None:
        out = _from_set(g, p, tables, s_set, o_set, options, stats, node_filter)
    elif not node_filter and options.executor == "auto" and (through := _through(g, p, options)) is not None:
        out = through
    elif p.fast_path and not node_filter:
        stats.fast_path = p.fast_path
        out = _shape(fastpaths.evaluate(g, p.expr, p.s, p.o), p, g)
    else:
        out = _traversed(g, p, tables, options, stats, node_filter)
    if tables.nfa.nullable and options.zero_length_unknown == "self":
        out = _with_unknown(g, p, out, s_set, o_set)
    return out.limit(options.limit) if options.limit is not None else out


def _at_node(p: RpqPlan):
    """(before, node, after) of a top-level concatenation with both ends open that must pass a node."""
    parts = p.expr.parts if isinstance(p.expr, Cat) else ()
    at = [i for i, x in enumerate(parts) if isinstance(x, At)]
    if p.s is not None or p.o is not None or not at or not 0 < at[0] < len(parts) - 1:
        return None
    join = lambda x: x[0] if len(x) == 1 else Cat(tuple(x))
    before, after = join(parts[: at[0]]), join(parts[at[0] + 1 :])
    # The condition holds wherever the step before it arrives, so only a plain step is split at;
    # a side with the empty path is left to the search.
    left = not isinstance(parts[at[0] - 1], Class) or isinstance(parts[at[0] + 1], At)
    return None if left or bitparallel.compile(after).nfa.nullable else (before, parts[at[0]].node, after)


def _through(g: Graph, p: RpqPlan, options: RpqOptions) -> DataFrame | None:
    """Both ends open and a node that every path passes: its starts, each with its ends, if the path is such."""
    if (found := _at_node(p)) is None:
        return None
    before, node, after = found
    rest = dataclasses.replace(options, limit=None)
    out = evaluate(g, before, o=node, options=rest).crossJoin(evaluate(g, after, s=node, options=rest))
    return out.filter("s = o").select("s") if p.same else out


def _with_unknown(g: Graph, p: RpqPlan, out: DataFrame, s_set, o_set) -> DataFrame:
    """Answers and the empty paths of constants, or members of sets, that are no nodes of the graph."""
    if s_set is not None or o_set is not None:
        (own, other), column = ((o_set, s_set), "s") if o_set is not None else ((s_set, None), "o")
        const = p.s if column == "s" else p.o
        own = own.select("node") if const is None else own.select("node").filter(F.col("node") == const)
        own = own if other is None else own.join(other.select("node"), "node", "left_semi")
        return out.union(own.select(F.col("node").alias(column))).distinct()
    if p.s is not None and p.o is not None:
        return out.select((F.col("found") | F.lit(p.s == p.o)).alias("found"))
    if p.s is None and p.o is None:
        return out
    column, const = ("s", p.o) if p.o is not None else ("o", p.s)
    return out.union(g.spark.createDataFrame([(const,)], f"{column} string")).distinct()


def _shape(pairs_: DataFrame, p: RpqPlan, g: Graph) -> DataFrame:
    """Distinct pairs (s, o) to the columns of the query's variables; what is left stays distinct."""
    if p.s is not None:
        pairs_ = pairs_.filter(F.col("s") == p.s)
    if p.o is not None:
        pairs_ = pairs_.filter(F.col("o") == p.o)
    if p.same:
        return pairs_.filter("s = o").select("s")
    if p.s is not None and p.o is not None:
        return pairs_.agg((F.count("*") > 0).alias("found"))
    return pairs_.select(*[c for c, v in (("s", p.s), ("o", p.o)) if v is None])


def counted(g: Graph, path: str | Expr, options: RpqOptions = RpqOptions()) -> DataFrame:
    """(answers): their number with both ends open. Pairs that are known as all pairs of two sets are
    counted by the sizes of these, not one by one."""
    p = plan(g, path, options=options)
    if options.limit is None and options.executor == "auto" and p.fast_path == "concat2" and (n := fastpaths.count2(g, *p.expr.parts)) is not None:
        return n
    tables = bitparallel.compile(p.expr, options.chunk_bits, options.mask_bits)
    if options.limit is None and options.visit == "bfs" and not p.fast_path and _at_node(p) is None and (rows := _edges(g, p, tables, options, None)) is not None:
        found = kernel.both_open(g.spark, rows, tables, p.start == "objects", _arrive(tables), timeout_s=options.timeout_s)
        if not tables.nfa.nullable:
            return found.rest.agg((F.count("*") + F.lit(found.known())).alias("answers"))
        rest = found.rest.filter("s <> o").agg(F.count("*").alias("n"))
        return rest.crossJoin(g.nodes().agg(F.count("*").alias("k"))).select((F.col("n") + F.col("k") + F.lit(found.known() - found.loops())).alias("answers"))
    return evaluate(g, path, options=options).agg(F.count("*").alias("answers"))


def _with_empty(g: Graph, pairs_: DataFrame) -> DataFrame:
    """Distinct pairs and the empty path of every node; no pair is looked for twice, so nothing is shuffled."""
    return pairs_.filter("s <> o").unionByName(g.nodes().select(F.col("node").alias("s"), F.col("node").alias("o")))


def _arrive(tables) -> dict[int, str]:
    return {tables.nfa.bit(q): n for q, n in tables.nfa.arrive.items()}


def _edges(g: Graph, p: RpqPlan, tables, options: RpqOptions, node_filter):
    """The pruned edges for the kernel, if it may run."""
    if options.executor not in ("auto", "kernel") or tables.wide or node_filter:
        return None
    rows = kernel.fetch(g, p.labels, options.kernel_edges)
    if rows is None and options.executor == "kernel":
        raise ValueError(f"over {options.kernel_edges} edges for the kernel")
    return rows


def _traversed(g: Graph, p: RpqPlan, tables, options: RpqOptions, stats: RunStats, node_filter) -> DataFrame:
    spark, nullable = g.spark, tables.nfa.nullable
    if options.executor == "ring" and not (tables.wide or node_filter or tables.nfa.arrive and p.o is None):
        if options.index_only and not ring.fits(g, options.kernel_edges):
            g = ring.of_labels(g, p.labels)
            if not ring.fits(g, options.kernel_edges):
                stats.extra["index"] = "in rounds over many shards"
                return ring.in_rounds(g, p, tables, options, stats)
        return ring.evaluate(g, p, tables, options, stats)
    rows = _edges(g, p, tables, options, node_filter)
    back = p.o is not None and p.start == "o"
    one = lambda name: spark.createDataFrame([(name,)], "node string")
    if p.s is None and p.o is None:
        if rows is not None:
            limit = None if p.same else options.limit
            if options.visit == "bfs":
                out = kernel.both_open(spark, rows, tables, p.start == "objects", _arrive(tables), limit, options.timeout_s).rows(limit)
            else:
                found = kernel.evaluate_local(spark, rows, tables, None, p.start == "objects", _arrive(tables), limit=limit, timeout_s=options.timeout_s, visit=options.visit)
                s, o = ("node", "origin") if p.start == "objects" else ("origin", "node")
                out = found.select(F.col(s).alias("s"), F.col(o).alias("o"))
            if nullable:
                out = _with_empty(g, out)
            return out.filter("s = o").select("s") if p.same else out
        label = None
        if options.rare_times and not node_filter and not _arrive(tables):
            counts = g.counts(p.labels)
            label = rare_label(p.expr, counts, options.rare_times)
            if label is None and sum(counts.get(x, 0) for x in p.labels) <= options.kernel_edges:
                # Counts that are near each other shift with the graph; where a split is one search for all starts, it need not be rare.
                label = inner_label(p.expr, counts)
        if label is not None:
            stats.extra["split at"] = label
            out = rare.split_evaluate(g, p.expr, label, options, stats)
            return out.filter("s = o").select("s") if p.same else out
        order = p.start if not p.expr or not _arrive(tables) else "subjects"
        reversed_tables = bitparallel.compile(rewrite.reverse(p.expr), options.chunk_bits, options.mask_bits) if order == "objects" else tables
        marks = _premarks(g, tables, node_filter)
        out = pairs.evaluate(g, tables, reversed_tables, dataclasses.replace(options, order="subjects" if marks is not None else order), stats, _arrive(tables), marks)
        return out.filter("s = o").select("s") if p.same else out
    if p.s is not None and p.o is not None:
        if rows is not None:
            found = kernel.evaluate_local(spark, rows, tables, one(p.o if back else p.s), back, _arrive(tables), timeout_s=options.timeout_s).filter(F.col("node") == (p.s if back else p.o)).select("node")
            if nullable and p.s == p.o:
                found = found.union(g.nodes().filter(F.col("node") == p.s))
            return found.agg((F.count("*") > 0).alias("found"))
        return _both_constant(g, p, tables, options, stats, back, node_filter)
    const, column = (p.o, "s") if p.o is not None else (p.s, "o")
    if rows is not None:
        found = kernel.evaluate_local(spark, rows, tables, one(const), p.o is not None, _arrive(tables), limit=options.limit, timeout_s=options.timeout_s, visit=options.visit).select(F.col("node").alias(column))
        if nullable:
            found = found.union(g.nodes().filter(F.col("node") == const).select(F.col("node").alias(column))).distinct()
        return found
    if p.o is not None:
        return _frontier(g, tables, one(const), options, stats, node_filter).select(F.col("node").alias(column))
    # A constant subject: the mirrored expression from there, backward.
    if _arrive(tables) or node_filter:
        return _forward(g, tables, one(const), options, stats, node_filter).select(F.col("node").alias(column))
    mirrored = bitparallel.compile(rewrite.reverse(p.expr), options.chunk_bits, options.mask_bits)
    return _frontier(g, mirrored, one(const), options, stats, None).select(F.col("node").alias(column))


def _premarks(g: Graph, tables, node_filter):
    """States that nodes must not enter, from the allowed nodes of positions."""
    if not node_filter:
        return None
    masks = Masks(tables)
    out = None
    for position, ok in node_filter.items():
        part = g.nodes().join(ok.select("node"), "node", "left_anti").select("node", masks.lit(tables.nfa.bit(position)).alias("mask"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("node").agg(masks.either("mask").alias("mask"))


def _frontier(g: Graph, tables, target: DataFrame, options, stats, node_filter) -> DataFrame:
    """(node): subjects from which some node of the target is reached."""
    masks = Masks(tables)
    known = target.select("node").join(g.nodes(), "node", "left_semi")
    seeds = backward.seeds_of(g, masks, known, tables.nfa.mask(tables.nfa.last))
    seen = backward.traverse(g, tables, seeds, [], True, options, stats, arrive=_arrive(tables), premarked=_premarks(g, tables, node_filter), report=tables.initial)
    found = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(tables.initial)))).select("node")
    return found.union(known).distinct() if tables.nfa.nullable else found


def _forward(g: Graph, tables, source: DataFrame, options, stats, node_filter) -> DataFrame:
    """(node): objects that are reached from some node of the source."""
    masks, last = Masks(tables), tables.nfa.mask(tables.nfa.last)
    known = source.select("node").join(g.nodes(), "node", "left_semi")
    seen = backward.traverse(g, tables, backward.seeds_of(g, masks, known, tables.initial), [], False, options, stats, arrive=_arrive(tables), premarked=_premarks(g, tables, node_filter), report=last)
    found = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(last)))).select("node")
    return found.union(known).distinct() if tables.nfa.nullable else found


def _from_set(g: Graph, p: RpqPlan, tables, s_set, o_set, options, stats, node_filter) -> DataFrame:
    # What the other end keeps is looked at last, so a limit must not end the search before.
    rest = dataclasses.replace(options, limit=None)
    if o_set is not None:
        out, const, other = _frontier(g, tables, o_set, rest, stats, node_filter).select(F.col("node").alias("s")), p.s, s_set
    else:
        out, const, other = _forward(g, tables, s_set, rest, stats, node_filter).select(F.col("node").alias("o")), p.o, None
    if const is not None:
        out = out.filter(F.col(out.columns[0]) == const)
    return out if other is None else out.join(other.select(F.col("node").alias("s")).distinct(), "s", "left_semi")


def _both_constant(g: Graph, p: RpqPlan, tables, options, stats, back, node_filter) -> DataFrame:
    spark, masks = g.spark, Masks(tables)
    yes = lambda x: spark.createDataFrame([(bool(x),)], "found boolean")
    known = {r.node for r in g.nodes().filter(F.col("node").isin(p.s, p.o)).collect()}
    if tables.nfa.nullable and p.s == p.o and p.s in known:
        return yes(True)
    if not {p.s, p.o} <= known:
        return yes(False)
    if options.bidirectional:
        return yes(meet(g, p, tables, options, stats, _premarks(g, tables, node_filter)))
    goal, bit = (p.s, tables.initial) if back else (p.o, tables.nfa.mask(tables.nfa.last))
    hit = lambda new: bool(new.filter((F.col("node") == goal) & masks.some(masks.both(F.col("mask"), masks.lit(bit)))).limit(1).count())
    start, first = (p.o, tables.nfa.mask(tables.nfa.last)) if back else (p.s, tables.initial)
    seeds = spark.createDataFrame([(start, masks.value(first))], f"node string, mask {masks.type}")
    found = []

    def stop(new):
        # Round 0 holds only the start, which is no answer by itself.
        if stats.rounds > 1 and hit(new):
            found.append(True)
        return bool(found)

    backward.traverse(g, tables, seeds, [], back, options, stats, stop=stop, arrive=_arrive(tables), premarked=_premarks(g, tables, node_filter))
    return yes(found)


def meet(g: Graph, p: RpqPlan, tables, options: RpqOptions, stats: RunStats, marks: DataFrame | None = None) -> bool:
    """Both constants: searches from both ends that take turns until they share a state of a node.

    Node conditions hold on both sides: must-pass nodes in the steps, ``marks`` in what is entered.
    """
    from . import state
    from .store import Store

    masks, store = Masks(tables), Store(g.spark, "meet")
    sides = []
    for back, node, mask in ((False, p.s, tables.initial), (True, p.o, tables.nfa.mask(tables.nfa.last))):
        seeds = backward.barred(g.spark.createDataFrame([(node, masks.value(mask))], f"node string, mask {masks.type}"), marks, masks).select("node", "mask")
        name = "back" if back else "ahead"
        edges = backward.steps(g, masks, back, options, _arrive(tables))
        front = store.save(seeds, f"{name}/0")
        seen = backward.Visited(store, masks, [])
        seen.add(front)
        sides.append({"back": back, "name": name, "k": 0, "front": front, "seen": seen, "edges": edges if g.is_stored else store.save(edges, f"edges_{name}")})
    while True:
        ahead, behind = (s["seen"].all() for s in sides)
        met = ahead.withColumnRenamed("mask", "a").join(behind.withColumnRenamed("mask", "b"), "node").filter(masks.some(masks.both(F.col("a"), F.col("b"))))
        if met.limit(1).count():
            return True
        sizes = [s["front"].count() for s in sides]
        if not all(sizes):
            return False
        side = sides[sizes.index(min(sizes))]
        stats.rounds += 1
        stats.frontier_rows += min(sizes)
        side["k"] += 1
        sent = F.broadcast(side["front"]) if min(sizes) <= options.broadcast_rows else side["front"]
        candidates = state.step(sent, side["edges"], masks, [], side["back"])
        new = state.fresh(backward.barred(candidates, marks, masks).select("node", "mask"), side["seen"].all(), masks, [])
        side["front"] = store.save(new, f"{side['name']}/{side['k']}")
        side["seen"].add(side["front"])


class Fluent:
    """``graph.path("a/b*").from_("x").to("y").run()``."""

    def __init__(self, g: Graph, path: str):
        self.g, self.text, self.s, self.o, self.options = g, path, None, None, RpqOptions()

    def from_(self, s: str | None) -> Fluent:
        self.s = s
        return self

    def to(self, o: str | None) -> Fluent:
        self.o = o
        return self

    def with_options(self, **options) -> Fluent:
        self.options = dataclasses.replace(self.options, **options)
        return self

    def explain(self) -> str:
        return plan(self.g, self.text, self.s, self.o, self.options).explain()

    def run(self) -> DataFrame:
        return evaluate(self.g, self.text, self.s, self.o, self.options)
