"""The kernel executor: the pruned edges, when their number is checked to be small, go
to every task once; each task runs its origins to the end, so there are no rounds.

Inside a task the edges are a sorted adjacency array. A level of the search is a
handful of array operations over (origin, node) cells; visited masks live in one array
that is zeroed cell by cell after use, never as a whole.

With both ends open most answers of a closure pass some large strongly connected part of the
product of graph and automaton. Whatever reaches a part (its starts) has as answers whatever the part
reaches (its ends), so these are kept as a block of starts and ends; the parts are then closed to the
searches, which find the pairs that pass none.
"""

from __future__ import annotations

import time
from dataclasses import dataclass
from itertools import batched, groupby
from operator import itemgetter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automaton.bitparallel import Tables
from ..graph.model import Graph

#: Cells (origin, node) that a task holds at a time.
CELLS = 1 << 22
#: Steps that a level of a search looks at together; a level of more is cut in two.
STEPS = 1 << 22
#: Cells (node, state) of a part that is worth a block, parts at most, and cells looked at in vain at most.
PART, PARTS, VAIN = 64, 64, 8
#: Starts, and ends, of a block that are named together, and rows of these that travel together.
TILE, TILES = 256, 32


@dataclass
class Local:
    """Steps of a pruned graph, sorted by the node they leave."""

    names: np.ndarray
    start: np.ndarray
    to: np.ndarray
    b: np.ndarray

    @classmethod
    def of(cls, at: np.ndarray, to: np.ndarray, b: np.ndarray, names: np.ndarray) -> Local:
        order = np.argsort(at, kind="stable")
        start = np.concatenate([[0], np.cumsum(np.bincount(at, minlength=len(names)))])
        return cls(names, start, to[order], b[order])


def fetch(g: Graph, labels: list[str], most: int) -> pa.Table | None:
    """Edges of the labels as an Arrow table, or None if there are more than ``most``.

    A stored graph knows the counts of its labels, so nothing is read beyond the bound, and what is
    read comes from all tasks; of another graph one row more than the bound is asked for.
    """
    rows = g.edges.filter(F.col("p").isin(labels))
    if g.is_stored:
        known = g.counts()
        return rows.toArrow() if sum(known.get(x, 0) for x in labels) <= most else None
    rows = rows.limit(most + 1).toArrow()
    return None if rows.num_rows > most else rows


def local(rows: pa.Table, tables: Tables, backward: bool, arrive: dict[int, str] | None = None) -> Local:
    both = pa.chunked_array([*rows.column("s").chunks, *rows.column("o").chunks], pa.string()).combine_chunks().dictionary_encode()
    names = both.dictionary.to_numpy(zero_copy_only=False)
    code, n = both.indices.to_numpy(), rows.num_rows
    s, o = code[:n].astype(np.int64), code[n:].astype(np.int64)
    labels = rows.column("p").combine_chunks().dictionary_encode() if n else pa.array([], pa.string()).dictionary_encode()
    own, p = labels.dictionary.to_pylist(), labels.indices.to_numpy()
    at, to, b = [], [], []
    for inverse in (False, True):
        table = np.array([tables.label(x, inverse) for x in own] or [0], np.int64)
        m = table[p] if n else np.empty(0, np.int64)
        hit = m != 0
        ends = (o, s) if backward != inverse else (s, o)
        at.append(ends[0][hit])
        to.append(ends[1][hit])
        b.append(m[hit])
    at, to, b = (np.concatenate(x) for x in (at, to, b))
    for bit, node in (arrive or {}).items():
        enters = at if backward else to
        away = names[enters] != node
        b = np.where(away, b & ~np.int64(bit), b)
    keep = b != 0
    return Local.of(at[keep], to[keep], b[keep], names)


class Search:
    """Searches over one local graph, in one direction."""

    def __init__(self, graph: Local, chunks: list[np.ndarray], chunk_bits: int, backward: bool):
        self.g, self.chunks, self.bits, self.backward = graph, chunks, chunk_bits, backward
        self.visited = np.empty(0, np.int64)
        self.levels = self.entered = self.states = self.tested = 0
        #: Time at which a search gives up.
        self.deadline: float | None = None

    def look(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), np.int64)
        for k, table in enumerate(self.chunks):
            out |= table[x >> k * self.bits & (len(table) - 1)]
        return out

    def run(self, origin: np.ndarray, node: np.ndarray, mask: np.ndarray, report: int, allowed: np.ndarray | None = None, order: str = "bfs", marks: np.ndarray | None = None):
        """(origin, node) pairs that got a state of ``report``, from seeds of one state set each.

        ``allowed``: per node, the states that it may enter. ``order``: bfs, or dfs,
        which pops one cell at a time and differs only in the sequence of visits. ``marks`` is filled
        with the states of each node, if there is one origin.
        """
        v, g = len(self.g.names), self.g
        cells = int(origin.max(initial=-1) + 1) * v
        if len(self.visited) < cells:
            self.visited = np.zeros(cells, np.int64)
        key, touched, hits = origin * v + node, [], []
        np.bitwise_or.at(self.visited, key, mask)
        stack = [(key, mask)]
        while stack:
            key, mask = stack.pop()
            if order == "dfs" and len(key) > 1:
                stack += [(key[i : i + 1], mask[i : i + 1]) for i in range(len(key) - 1, -1, -1)]
                continue
            if self.deadline is not None and time.monotonic() > self.deadline:
                raise TimeoutError("the time limit is over")
            at = key % v
            n = g.start[at + 1] - g.start[at]
            total = int(n.sum())
            if total > STEPS and len(key) > 1:
                half = len(key) // 2
                stack += [(key[half:], mask[half:]), (key[:half], mask[:half])]
                continue
            touched.append(key)
            self.levels += 1
            self.entered += len(key)
            self.states += int(np.bitwise_count(mask).sum())
            hits.append(key[mask & report != 0])
            if not total:
                continue
            row = np.repeat(np.arange(len(key)), n)
            edge = np.arange(total) - np.repeat(np.cumsum(n) - n, n) + g.start[at][row]
            self.tested += total
            if self.backward:
                x = mask[row] & g.b[edge]
                ok = x != 0
                new = self.look(x[ok])
            else:
                new = self.look(mask)[row] & g.b[edge]
                ok = new != 0
                new = new[ok]
            to = g.to[edge[ok]]
            if allowed is not None:
                new &= allowed[to]
            cell = (key - at)[row[ok]] + to
            new &= ~self.visited[cell]
            ok = new != 0
            cell, new = cell[ok], new[ok]
            if len(cell):
                sort = np.argsort(cell, kind="stable")
                cell, new = cell[sort], new[sort]
                first = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))
                cell, new = cell[first], np.bitwise_or.reduceat(new, first)
                self.visited[cell] |= new
                stack.append((cell, new))
        found = np.unique(np.concatenate(hits)) if hits else np.empty(0, np.int64)
        if marks is not None:
            marks[:] = self.visited[:v]
        if touched:
            self.visited[np.concatenate(touched)] = 0
        return found // v, found % v


@dataclass
class Part:
    """A strongly connected part: the nodes whose searches meet it, and those that it gives as answers."""

    starts: np.ndarray
    ends: np.ndarray


def parts_of(ahead: Local, behind: Local, tables: Tables) -> tuple[list[Part], np.ndarray]:
    """Large strongly connected parts of the product, and per node the states outside of them.

    ``ahead``, ``behind``: the steps along the path and against it. A part is what a cell reaches and is
    reached from; cells with many steps in and out are tried first. Later parts are found with the
    earlier ones closed, as what passes those is known.
    """
    v, states = len(ahead.names), tables.bits
    allowed = np.full(v, -1, np.int64)
    loops = list(tables.succ)
    for k in range(states):
        loops = [x | (loops[k] if x >> k & 1 else 0) for x in loops]
    own = [q for q in range(states) if loops[q] >> q & 1]
    if not own or not len(ahead.to):
        return [], allowed
    searches = [Search(ahead, tables.arrays(False), tables.chunk_bits, False), Search(behind, tables.arrays(True), tables.chunk_bits, True)]
    leaves = np.repeat(np.arange(v), np.diff(ahead.start))
    scores = []
    for q in own:
        into = np.bincount(ahead.to[ahead.b >> q & 1 != 0], minlength=v)
        out = np.bincount(leaves[ahead.b & np.int64(tables.succ[q]) != 0], minlength=v)
        scores.append(into * out)
    best = np.stack(scores)
    found: list[Part] = []
    vain, last = 0, tables.nfa.mask(tables.nfa.last)
    while len(found) < PARTS and vain < VAIN:
        row, node = np.unravel_index(int(best.argmax()), best.shape)
        if not best[row, node]:
            break
        marks = []
        for search in searches:
            marks.append(np.zeros(v, np.int64))
            search.run(np.zeros(1, np.int64), np.array([node]), np.array([1 << own[row]], np.int64), 0, allowed, marks=marks[-1])
        part = marks[0] & marks[1]
        for k, q in enumerate(own):
            best[k][part >> q & 1 != 0] = 0
        if int(np.bitwise_count(part).sum()) < PART:
            vain += 1
            continue
        found.append(Part(marks[1] & np.int64(tables.initial) != 0, marks[0] & np.int64(last) != 0))
        allowed &= ~part
    return found, allowed


def blocks_of(parts: list[Part]) -> list[tuple[np.ndarray, np.ndarray]]:
    """(starts, ends) as numbers of nodes; no pair lies in two blocks."""
    out = []
    for k, part in enumerate(parts):
        starts = np.flatnonzero(part.starts)
        before = np.stack([p.starts[starts] for p in parts[:k]], axis=1) if k else np.zeros((len(starts), 0), bool)
        kinds, which = np.unique(before, axis=0, return_inverse=True) if k else (before[:1], np.zeros(len(starts), np.int64))
        for i, kind in enumerate(kinds):
            ends = part.ends.copy()
            for j in np.flatnonzero(kind):
                ends &= ~parts[j].ends
            if ends.any():
                out.append((starts[which.ravel() == i], np.flatnonzero(ends)))
    return out


@dataclass
class Pairs:
    """Answers with both ends open: blocks of all pairs of some starts and ends, and the pairs in none."""

    spark: SparkSession
    names: np.ndarray
    blocks: list[tuple[np.ndarray, np.ndarray]]
    rest: DataFrame

    def known(self) -> int:
        """Number of pairs in blocks."""
        return sum(len(a) * len(b) for a, b in self.blocks)

    def loops(self) -> int:
        """Number of pairs in blocks of a node with itself."""
        return sum(len(np.intersect1d(a, b)) for a, b in self.blocks)

    def rows(self, limit: int | None = None) -> DataFrame:
        """(s, o); with a limit no more than what gives so many."""
        if not self.blocks:
            return self.rest
        sent = self.spark.sparkContext.broadcast((self.names, self.blocks))
        schema = pa.schema([("s", pa.list_(pa.string())), ("o", pa.list_(pa.string()))])

        def work(batches):
            named, blocks = sent.value
            named = pa.array(named, pa.string())
            tile = lambda x, i: named.take(pa.array(x[i : i + TILE]))
            many = lambda parts: pa.ListArray.from_arrays(np.cumsum([0, *map(len, parts)]).astype(np.int32), pa.concat_arrays(parts))
            for b in batches:
                for k, i in zip(*(c.to_pylist() for c in b.columns)):
                    starts, ends = tile(blocks[k][0], i), blocks[k][1]
                    for lo in range(0, len(ends), TILE * TILES):
                        tiles = [tile(ends, j) for j in range(lo, min(lo + TILE * TILES, len(ends)), TILE)]
                        yield pa.RecordBatch.from_arrays([many([starts] * len(tiles)), many(tiles)], schema=schema)

        at = [(k, i) for k, (starts, _) in enumerate(self.blocks) for i in range(0, len(starts), TILE)]
        rows = self.spark.createDataFrame(pa.table({"k": pa.array([k for k, _ in at], pa.int64()), "i": pa.array([i for _, i in at], pa.int64())}))
        tiles = rows.repartition(max(1, min(len(at), 8 * self.spark.sparkContext.defaultParallelism))).mapInArrow(work, "s array<string>, o array<string>")
        out = tiles.select(F.explode("s").alias("s"), "o").select("s", F.explode("o").alias("o"))
        return out if limit is not None and self.known() >= limit else out.unionByName(self.rest)


def both_open(spark: SparkSession, rows: pa.Table, tables: Tables, backward: bool, arrive=None, limit: int | None = None, timeout_s: float | None = None) -> Pairs:
    """All answers but those of the expression's empty path; ``backward``: searches start at objects."""
    sides = [local(rows, tables, back, arrive) for back in (False, True)]
    parts, allowed = parts_of(*sides, tables)
    blocks = blocks_of(parts)
    pairs = Pairs(spark, sides[0].names, blocks, None)
    if limit is not None:
        limit = limit if pairs.known() < limit else 0
    found = evaluate_local(spark, rows, tables, None, backward, arrive, limit=limit, timeout_s=timeout_s, graph=sides[backward], closed=(parts, allowed) if parts else None)
    s, o = ("node", "origin") if backward else ("origin", "node")
    pairs.rest = found.select(F.col(s).alias("s"), F.col(o).alias("o"))
    return pairs


def evaluate_local(spark: SparkSession, rows: pa.Table, tables: Tables, origins: DataFrame | None, backward: bool, arrive=None, useful: np.ndarray | None = None, chunk: int | None = None, limit: int | None = None, timeout_s: float | None = None, visit: str = "bfs", graph: Local | None = None, closed: tuple[list[Part], np.ndarray] | None = None) -> DataFrame:
    """(origin, node) reached from each origin; the expression's empty path is not included.

    ``origins``: (node), or (node, at) with a row for each node ``at`` which its search starts, the rows of a node together; None: every node that may start. ``closed``: parts whose pairs
    are left out, and the states outside of them. Backward searches start in the
    final states and report the initial one; forward the other way. ``limit``: a task ends
    after so many answers; ``timeout_s``: a task that searches longer fails.
    """
    graph = local(rows, tables, backward, arrive) if graph is None else graph
    last = tables.nfa.mask(tables.nfa.last)
    start, report = (last, tables.initial) if backward else (tables.initial, last)
    v = max(1, len(graph.names))
    size = chunk or max(1, min(4096, CELLS // v))
    sent = spark.sparkContext.broadcast((graph, tables.arrays(backward), tables.chunk_bits, {n: i for i, n in enumerate(graph.names)}, closed))
    schema = pa.schema([("origin", pa.string()), ("node", pa.string())])
    if origins is None:
        # A node may start if it has a step from the starting states at all.
        if backward:
            ok = graph.b & start != 0
        else:
            first = tables._look(tables.T, tables.initial)
            ok = graph.b & first != 0
        at = np.repeat(np.arange(len(graph.names)), np.diff(graph.start))
        nodes = np.unique(at[ok])
        if useful is not None:
            nodes = np.intersect1d(nodes, useful)
        parts = max(1, min(spark.sparkContext.defaultParallelism, -(-len(nodes) // 64)))
        origins = spark.createDataFrame(pa.table({"node": pa.array(graph.names[nodes], pa.string())})) if len(nodes) else spark.createDataFrame([], "node string")
        origins = origins.repartition(parts)

    def work(batches):
        graph, chunks, bits, ids, closed = sent.value
        parts, allowed = closed if closed is not None else ([], None)
        search, left = Search(graph, chunks, bits, backward), limit
        search.deadline = None if timeout_s is None else time.monotonic() + timeout_s
        named = pa.array(graph.names, pa.string())

        def seeds():
            if not together:
                yield from ((n, [ids[n]]) for b in batches for n in b.column(0).to_pylist() if n in ids)
                return
            rows = (row for b in batches for row in zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
            for n, own in groupby(rows, itemgetter(0)):
                if at := [ids[x] for _, x in own if x in ids]:
                    yield n, at

        for part in batched(seeds(), size):
            if left is not None and left <= 0:
                return
            at = np.array([k for _, ks in part for k in ks], np.int64)
            key = np.repeat(np.arange(len(part)), [len(ks) for _, ks in part])
            mask = np.full(len(at), start, np.int64)
            if allowed is not None:
                mask &= allowed[at]
                key, at, mask = key[mask != 0], at[mask != 0], mask[mask != 0]
            o, n = search.run(key, at, mask, report, allowed, order=visit)
            for p in parts:
                first = np.array([ks[0] for _, ks in part], np.int64)[o]
                new = ~(p.starts[n] & p.ends[first]) if backward else ~(p.starts[first] & p.ends[n])
                o, n = o[new], n[new]
            left = None if left is None else left - len(o)
            names = pa.array([x for x, _ in part], pa.string())
            for j in range(0, len(o), 100_000):
                yield pa.RecordBatch.from_arrays([names.take(pa.array(o[j : j + 100_000])), named.take(pa.array(n[j : j + 100_000]))], schema=schema)

    together = "at" in origins.columns
    return origins.mapInArrow(work, "origin string, node string")
