"""The index executor: path queries on the cyclic triple index itself.

A shard of the index holds two columns as wavelet trees, labels in the order (o, s, p) and
subjects in the order (p, o, s), and the counts before each object and each label; edges and
their inverses, as numbers. From the range of an object: the labels that lead to it and
enter an active state (a subtree of the labels' tree is left where the OR of its masks
misses the states); by each label the range of its subjects, and those among them that lack some of
the new states (a subtree is left where the AND of its visited masks has them all); and each
of those as an object again, by the counts. Nothing but numbers is touched until answers are named.

Subtrees are walked level by level for all ranges of a search step at once, as arrays. A shard is
sent to the tasks, so its number of edges is checked first (``RpqOptions.kernel_edges``);
for larger graphs the planner picks another executor (:func:`fits`), or the shards of the
index are searched in rounds (:func:`in_rounds`). :func:`visits` walks one range at a time, in the order of the search.
"""

from __future__ import annotations

import dataclasses
from collections import deque
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..automaton import bitparallel
from ..automaton.bitparallel import Masks, Tables
from ..graph.model import Graph
from ..index import wavelet
from ..lang import rewrite
from ..lang.ast import Class, Plus, Star
from . import backward, kernel, state


@dataclass
class Shard:
    """Numbers start at 0; an inverse label is its label plus the number of labels."""

    names: np.ndarray
    labels: list[str]
    Lp: wavelet.Wavelet
    Ls: wavelet.Wavelet
    Co: np.ndarray
    Cp: np.ndarray

    @classmethod
    def of(cls, rows: pa.Table) -> Shard:
        both = pa.chunked_array([*rows.column("s").chunks, *rows.column("o").chunks], pa.string())
        names = np.array(sorted(both.unique().to_pylist()), object)
        at, labels = {x: i for i, x in enumerate(names)}, sorted(rows.column("p").unique().to_pylist())
        number = {x: i for i, x in enumerate(labels)}
        s, o = (np.array([at[x] for x in rows.column(c).to_pylist()], np.int64) for c in "so")
        p = np.array([number[x] for x in rows.column("p").to_pylist()], np.int64)
        return cls.numbered(np.concatenate([s, o]), np.concatenate([p, p + len(labels)]), np.concatenate([o, s]), names, labels)

    @classmethod
    def numbered(cls, s, p, o, names, labels) -> Shard:
        """From completed edges as numbers."""
        v, sigma = max(1, len(names)), max(1, 2 * len(labels))
        count = lambda x, n: np.concatenate([[0], np.cumsum(np.bincount(x, minlength=n))]).astype(np.int64)
        return cls(names, labels, wavelet.Wavelet(p[np.lexsort((p, s, o))], sigma), wavelet.Wavelet(s[np.lexsort((s, o, p))], v), count(o, v), count(p, sigma))

    def masks(self, tables: Tables) -> dict[int, int]:
        """States that each numbered label enters."""
        n = len(self.labels)
        got = {i + inverse * n: tables.label(x, bool(inverse)) for i, x in enumerate(self.labels) for inverse in (0, 1)}
        return {i: m for i, m in got.items() if m}

    def nbytes(self) -> int:
        return self.Lp.nbytes() + self.Ls.nbytes() + self.Co.nbytes + self.Cp.nbytes


def visits(shard: Shard, tables: Tables, o: int, order: str = "bfs"):
    """(node, states that are new to it) in the order of the search from object ``o``; bfs or dfs."""
    chosen, last = shard.masks(tables), tables.nfa.mask(tables.nfa.last)
    below = wavelet.label_masks(shard.Lp.height, chosen)
    seen = wavelet.no_states(shard.Ls.height, set(range(len(shard.names))))
    wavelet.mark(seen, o, last, shard.Ls.height)
    todo = deque([(o, last)])
    while todo:
        node, d = todo.popleft() if order == "bfs" else todo.pop()
        found = []
        for label, b, e in shard.Lp.distinct_masked(int(shard.Co[node]), int(shard.Co[node + 1]), d, below):
            after = tables._look(tables.R, d & chosen[label])
            base = int(shard.Cp[label])
            found += shard.Ls.distinct_unvisited(base + b, base + e, after, seen) if after else []
        yield from found
        todo.extend(found if order == "bfs" else reversed(found))


@dataclass
class Search:
    """Searches over a shard by one automaton, backward from objects."""

    shard: Shard
    tables: Tables
    #: Work: steps, ranges of labels and of subjects met, tree nodes looked at, tree nodes left.
    counts: dict = field(default_factory=lambda: dict.fromkeys(("steps", "labels", "subjects", "looked", "pruned"), 0))

    def __post_init__(self):
        shard, t = self.shard, self.tables
        self.last = t.nfa.mask(t.nfa.last)
        self.below = [np.array(x, np.int64) for x in wavelet.label_masks(shard.Lp.height, shard.masks(t))]
        self.chunks = t.arrays(True)
        # Leaves for numbers that no node has count as visited in every state.
        fresh = [np.array(x, np.int64) for x in wavelet.no_states(shard.Ls.height, set(range(len(shard.names))))]
        at = {n: i for i, n in enumerate(shard.names)}
        for q, name in t.nfa.arrive.items():
            # A state with a must-pass node is never entered elsewhere.
            away = np.arange(len(shard.names)) != at.get(name, -1)
            fresh[-1][: len(shard.names)][away] |= t.nfa.bit(q)
        for level in range(shard.Ls.height - 1, -1, -1):
            fresh[level] = fresh[level + 1][0::2] & fresh[level + 1][1::2]
        self.fresh, self.seen = fresh, [x.copy() for x in fresh]

    def close(self, nodes: np.ndarray) -> None:
        """Nodes that count as visited in every state from now on."""
        self.fresh[-1][nodes] = -1
        for level in range(self.shard.Ls.height - 1, -1, -1):
            self.fresh[level] = self.fresh[level + 1][0::2] & self.fresh[level + 1][1::2]
        self.seen = [x.copy() for x in self.fresh]

    def _look(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), np.int64)
        for k, table in enumerate(self.chunks):
            out |= table[x >> k * self.tables.chunk_bits & len(table) - 1]
        return out

    def _leaves(self, tree: wavelet.Wavelet, b: np.ndarray, e: np.ndarray, lets: callable):
        """(range, symbol, b, e) of the leaves of all ranges whose every tree node ``lets`` through."""
        item, prefix = np.arange(len(b)), np.zeros(len(b), np.int64)
        for level in range(tree.height + 1):
            keep = (e > b) & lets(level, prefix, item)
            self.counts["looked"] += len(b)
            self.counts["pruned"] += int(len(b) - keep.sum())
            item, prefix, b, e = item[keep], prefix[keep], b[keep], e[keep]
            if level == tree.height or not len(b):
                break
            bits, at = tree.levels[level], tree.starts[level][prefix]
            base = bits.rank1(at)
            ones_b, ones_e = bits.rank1(at + b) - base, bits.rank1(at + e) - base
            item, prefix = np.concatenate([item, item]), np.concatenate([prefix * 2, prefix * 2 + 1])
            b, e = np.concatenate([b - ones_b, ones_b]), np.concatenate([e - ones_e, ones_e])
        return item, prefix, b, e

    def _mark(self, nodes: np.ndarray, states: np.ndarray) -> None:
        """Adds states to distinct leaves; a node above becomes the AND of its two children."""
        self.seen[-1][nodes] |= states
        self.touched.append(nodes)
        for level in range(self.shard.Ls.height - 1, -1, -1):
            nodes = np.unique(nodes >> 1)
            self.seen[level][nodes] = self.seen[level + 1][2 * nodes] & self.seen[level + 1][2 * nodes + 1]

    def step(self, objects: np.ndarray, states: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place in ``objects``, subject, states that it gets) of one step, whatever was visited."""
        shard = self.shard
        item, label, lb, le = self._leaves(shard.Lp, shard.Co[objects], shard.Co[objects + 1], lambda level, prefix, i: self.below[level][prefix] & states[i] != 0)
        after, base = self._look(states[item] & self.below[-1][label]), shard.Cp[label]
        of, node, *_ = self._leaves(shard.Ls, base + lb, base + le, lambda level, prefix, i: after[i] != 0)
        return item[of], node, after[of]

    def run(self, lo: int, hi: int, goal: int | None = None, limit: int | None = None) -> np.ndarray:
        """Subjects from which some object with lo <= number < hi is reached by one step or more, sorted.

        ``goal``: ends once this subject is found; ``limit``: once so many are.
        """
        shard, self.touched = self.shard, []
        own = np.arange(lo, hi)
        states = self.last & ~self.seen[-1][own]
        own, states = own[states != 0], states[states != 0]
        self._mark(own, states)
        # All objects with the same states are one range, as their numbers are neighbours.
        if len(own) == hi - lo and len(own) and (states == states[0]).all():
            b, e, d = shard.Co[[lo]], shard.Co[[hi]], states[:1]
        else:
            b, e, d = shard.Co[own], shard.Co[own + 1], states
        hits: list[np.ndarray] = []
        n_hits = 0
        while len(b):
            self.counts["steps"] += 1
            item, label, lb, le = self._leaves(shard.Lp, b, e, lambda level, prefix, item: self.below[level][prefix] & d[item] != 0)
            after = self._look(d[item] & self.below[-1][label])
            base = shard.Cp[label]
            self.counts["labels"] += len(label)
            of, node, *_ = self._leaves(shard.Ls, base + lb, base + le, lambda level, prefix, i: after[i] & ~self.seen[level][prefix] != 0)
            new = after[of] & ~self.seen[-1][node]
            order = np.argsort(node, kind="stable")
            node, new = node[order], new[order]
            first = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]])) if len(node) else np.empty(0, np.int64)
            if not len(first):
                break
            node, new = node[first], np.bitwise_or.reduceat(new, first)
            self.counts["subjects"] += len(node)
            self._mark(node, new)
            hit = node[new & self.tables.initial != 0]
            hits.append(hit)
            n_hits += len(hit)
            if goal is not None and (hit == goal).any() or limit is not None and n_hits >= limit:
                break
            b, e, d = shard.Co[node], shard.Co[node + 1], new
        # Only what was written is set back.
        nodes = np.unique(np.concatenate(self.touched)) if self.touched else np.empty(0, np.int64)
        for level in range(shard.Ls.height, -1, -1):
            self.seen[level][nodes] = self.fresh[level][nodes]
            nodes = np.unique(nodes >> 1)
        return np.unique(np.concatenate(hits)) if hits else np.empty(0, np.int64)


def fits(g: Graph, most: int) -> bool:
    """Whether the graph is one shard: by its stored counts, else by a bounded read."""
    if g._shard is not None:
        return True
    return (sum(g.counts().values()) if g.is_stored else g.edges.limit(most + 1).count()) <= most


def shard_of(g: Graph, most: int) -> Shard:
    """The graph's shard, built once; its edges are counted while they are read, up to the bound."""
    if g._shard is None:
        rows = g.edges.limit(most + 1).toArrow()
        if rows.num_rows > most:
            raise ValueError(f"over {most} edges for one shard of the index")
        g._shard = Shard.of(rows)
    return g._shard


def answers(g: Graph, tables: Tables, ends: np.ndarray, options, goal: int | None = None, closed: np.ndarray | None = None) -> DataFrame:
    """(end, node): by names, the subjects from which each of some objects (numbers) is reached by a step or more.

    ``closed``: nodes (numbers) that no search enters. With a limit a task ends after so many answers.
    """
    spark, shard = g.spark, g._shard
    sent = spark.sparkContext.broadcast((shard, tables))
    schema = pa.schema([("end", pa.string()), ("node", pa.string())])
    limit = options.limit

    def work(batches):
        shard, tables = sent.value
        search, left = Search(shard, tables), limit
        if closed is not None:
            search.close(closed)
        for b in batches:
            for i in b.column(0).to_pylist():
                if left is not None and left <= 0:
                    return
                found = search.run(i, i + 1, goal, limit)
                left = None if left is None else left - len(found)
                for k in range(0, len(found), 100_000):
                    part = shard.names[found[k : k + 100_000]]
                    yield pa.RecordBatch.from_arrays([pa.array([shard.names[i]] * len(part), pa.string()), pa.array(part, pa.string())], schema=schema)

    parts = max(1, min(spark.sparkContext.defaultParallelism, -(-len(ends) // 64)))
    rows = spark.createDataFrame(pa.table({"id": pa.array(ends, pa.int64())})).repartition(parts)
    return rows.mapInArrow(work, "end string, node string")


def knot(shard: Shard, tables: Tables, mirrored: Tables, sources: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """(starts, ends) of a large strongly connected part, for the closure of one step: what reaches a node of the
    part, and what that node reaches; nodes with many edges are tried first."""
    search, turned = Search(shard, tables), Search(shard, mirrored)
    for i in sources[np.argsort(-np.diff(shard.Co)[sources], kind="stable")][: kernel.VAIN].tolist():
        starts, ends = search.run(i, i + 1), turned.run(i, i + 1)
        if len(np.intersect1d(starts, ends)) >= kernel.PART:
            return starts, ends
    return None


def evaluate(g: Graph, p, tables: Tables, options, stats) -> DataFrame:
    """Answers of a plan on the graph's shard."""
    spark, shard = g.spark, shard_of(g, options.kernel_edges)
    at = {x: i for i, x in enumerate(shard.names)}
    nullable = tables.nfa.nullable
    mirrored = lambda: bitparallel.compile(rewrite.reverse(p.expr), options.chunk_bits, options.mask_bits)
    number = lambda x: np.array([at[x]] if x in at else [], np.int64)
    if p.s is not None and p.o is not None:
        goal = at.get(p.s)
        found = answers(g, tables, number(p.o) if goal is not None else number(None), options, goal).filter(F.col("node") == p.s).select("node")
        if nullable and p.s == p.o:
            found = found.union(g.nodes().filter(F.col("node") == p.s))
        return found.agg((F.count("*") > 0).alias("found"))
    if p.s is not None or p.o is not None:
        if tables.nfa.arrive and p.s is not None:
            raise ValueError("must-pass nodes name the forward states; ask from the object, or use the frontier")
        const, column, t = (p.o, "s", tables) if p.o is not None else (p.s, "o", mirrored())
        out = answers(g, t, number(const), options).select(F.col("node").alias(column))
        if nullable:
            out = out.union(g.nodes().filter(F.col("node") == const)).distinct()
        return out
    # Both open: the whole range at once gives the useful subjects, then each asks for its objects.
    if tables.nfa.arrive:
        raise ValueError("must-pass nodes with both ends open go by the frontier")
    first = Search(shard, tables)
    sources = first.run(0, len(shard.names))
    stats.extra.update(first.counts)
    part = knot(shard, tables, mirrored(), sources) if isinstance(p.expr, (Star, Plus)) and isinstance(p.expr.body, Class) else None
    whole = dataclasses.replace(options, limit=None)
    if part is None:
        out = answers(g, mirrored(), sources, whole if p.same else options).select(F.col("end").alias("s"), F.col("node").alias("o"))
    else:
        # All starts of the part have all its ends as answers; the other pairs are searched without it.
        starts, ends = part
        inside, limit = np.intersect1d(starts, ends), None if p.same else options.limit
        rest = answers(g, mirrored(), np.setdiff1d(sources, inside), whole, closed=inside).select(F.col("end").alias("s"), F.col("node").alias("o"))
        both = [spark.createDataFrame(pa.table({"k": pa.array(shard.names[x], pa.string())})) for x in part]
        for c, x in zip("so", both):
            rest = rest.join(F.broadcast(x.select(F.col("k").alias(c), F.lit(True).alias(f"_{c}"))), c, "left")
        rest = rest.filter("_s IS NULL OR _o IS NULL").select("s", "o")
        out = kernel.Pairs(spark, shard.names, [part], rest).rows(limit)
    if nullable:
        out = out.filter("s <> o").unionByName(g.nodes().select(F.col("node").alias("s"), F.col("node").alias("o")))
    return out.filter("s = o").select("s") if p.same else out


def of_labels(g: Graph, names: list[str]) -> Graph:
    """The graph of some labels, over the nodes of the whole."""
    return Graph(g.edges.filter(F.col("p").isin(names)), names, g.nodes(), {x: n for x, n in g.counts(names).items() if x in names}, g.is_stored)


def in_rounds(g: Graph, p, tables: Tables, options, stats, edges_of_shard: int = 250_000) -> DataFrame:
    """Answers of a plan on an index of many shards, dealt by object: a step of the search is a job, in which each
    shard walks its own trees for the objects that lie there."""
    spark, labels, nullable = g.spark, g.labels(), tables.nfa.nullable
    mirror = p.s is not None and p.o is None
    t = bitparallel.compile(rewrite.reverse(p.expr), options.chunk_bits, options.mask_bits) if mirror else tables
    masks, n = Masks(t), max(1, -(-2 * sum(g.counts().values()) // edges_of_shard))
    shard = lambda c: F.pmod(F.xxhash64(c), F.lit(n)).alias("k")
    turned = g.edges.select(shard("s"), F.col("o").alias("s"), "p", F.lit(1).alias("inverse"), F.col("s").alias("o"))
    edges = g.edges.select(shard("o"), "s", "p", F.lit(0).alias("inverse"), "o").unionByName(turned)
    schema = pa.schema([("origin", pa.string()), ("node", pa.string()), ("mask", pa.int64())])

    def work(asked: pa.Table, rows: pa.Table) -> pa.Table:
        if not asked.num_rows or not rows.num_rows:
            return schema.empty_table()
        both = pa.chunked_array([*rows.column("s").chunks, *rows.column("o").chunks], pa.string()).combine_chunks().dictionary_encode()
        code = both.indices.to_numpy().astype(np.int64)
        number = {x: i for i, x in enumerate(labels)}
        label = np.array([number[x] for x in rows.column("p").to_pylist()], np.int64) + len(labels) * rows.column("inverse").to_numpy()
        search = Search(Shard.numbered(code[: rows.num_rows], label, code[rows.num_rows :], both.dictionary.to_numpy(zero_copy_only=False), labels), t)
        at = pc.index_in(asked.column("node").combine_chunks(), both.dictionary)
        here = np.flatnonzero(at.is_valid().to_numpy(zero_copy_only=False))
        of, node, mask = search.step(at.fill_null(0).to_numpy()[here].astype(np.int64), asked.column("mask").to_numpy()[here])
        return pa.Table.from_arrays([asked.column("origin").combine_chunks().take(pa.array(here[of])), both.dictionary.take(pa.array(node)), pa.array(mask, pa.int64())], schema=schema)

    def step(frontier: DataFrame) -> DataFrame:
        asked = frontier.select(shard("node"), "origin", "node", "mask")
        return state.merged(asked.groupBy("k").cogroup(edges.groupBy("k")).applyInArrow(work, "origin string, node string, mask long"), masks, ["origin"])

    const = p.s if mirror else p.o
    ends = g.nodes() if const is None else g.nodes().filter(F.col("node") == const)
    seeds = ends.select(F.col("node").alias("origin"), "node", masks.lit(t.nfa.mask(t.nfa.last)).alias("mask"))
    seen = backward.traverse(g, t, seeds, ["origin"], True, dataclasses.replace(options, limit=None), stats, step=step)
    found = seen.filter(masks.some(masks.both(F.col("mask"), masks.lit(t.initial)))).select("origin", "node")
    if nullable:
        found = found.union(ends.select(F.col("node").alias("origin"), "node")).distinct()
    if p.s is not None and p.o is not None:
        return found.filter(F.col("node") == p.s).agg((F.count("*") > 0).alias("found"))
    if const is not None:
        return found.select(F.col("node").alias("o" if mirror else "s"))
    out = found.select(F.col("node").alias("s"), F.col("origin").alias("o"))
    return out.filter("s = o").select("s") if p.same else out


def next_subject(shard: Shard, tables: Tables, mirrored: Tables, lower: int, goal: int) -> int | None:
    """The smallest subject >= lower from which the goal is reached, by bisection of ranges of subjects:
    a range holds one if the mirrored search from the whole range at once meets the goal."""
    search = Search(shard, mirrored)
    holds = lambda lo, hi: bool((search.run(lo, hi, goal) == goal).any()) or tables.nfa.nullable and lo <= goal < hi
    lo, hi = lower, len(shard.names)
    if lo >= hi or not holds(lo, hi):
        return None
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if holds(lo, mid) else (mid, hi)
    return lo


__all__ = ["Search", "Shard", "answers", "evaluate", "fits", "in_rounds", "next_subject", "shard_of", "visits"]
