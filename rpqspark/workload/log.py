"""Query logs: clean-up, and a synthetic log with the published pattern frequencies."""

from __future__ import annotations

import dataclasses
import time

from pyspark.errors import PythonException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec import keyed, planner
from ..exec.backward import Timeout
from ..exec.options import RpqOptions
from ..graph.model import Graph
from ..lang import patterns, rewrite
from ..lang.parser import parse
from .table1 import FREQUENCIES, QUERIES, Query


def clean(queries: DataFrame, nodes: DataFrame) -> DataFrame:
    """(s, path, o) without trivial paths, unknown constants and repeats; variables become null."""
    hard = F.udf(lambda p: not patterns.trivial(p), "boolean", useArrow=True)
    q = queries.select(*[F.when(F.col(c).startswith("?"), None).otherwise(F.col(c)).alias(c) for c in ("s", "o")], F.regexp_replace("path", r"\s+", "").alias("path"))
    q = q.dropDuplicates(["s", "path", "o"]).filter(hard("path"))
    for c in ("s", "o"):
        known = nodes.select(F.col("node").alias(f"_{c}"))
        q = q.join(known, q[c] == known[f"_{c}"], "left").filter(F.col(c).isNull() | F.col(f"_{c}").isNotNull()).drop(f"_{c}")
    return q.select("s", "path", "o")


def models(total: int = 200) -> list[tuple[str, str, Query, int]]:
    """(pattern, kind of constants, model, number of queries): each pattern as often as in the
    published log, scaled to ``total``, dealt over the workload's queries of that pattern."""
    share, out = total / sum(FREQUENCIES.values()), []
    for pattern, n in FREQUENCIES.items():
        own = [q for q in QUERIES.values() if patterns.classify(q.s, q.path, q.o) == pattern]
        n = max(1, round(n * share))
        for k, q in enumerate(own):
            if count := len(range(k, n, len(own))):
                out.append((pattern, (q.s or q.o or "").split(":")[0], q, count))
    return out


def constants(g: Graph, kind: str, n: int) -> DataFrame:
    """(node): n nodes of a kind, the first by the hash of their names, so that a log is reproducible."""
    return g.nodes().filter(F.substring_index("node", ":", 1) == kind).orderBy(F.md5("node")).limit(n)


def generate(graphs: dict[str, Graph], total: int = 200) -> list[tuple[str, str, str | None, str, str | None]]:
    """(id, graph, s, path, o) of a synthetic log. It is a list of queries, ``total`` about."""
    out = []
    for _, kind, q, n in models(total):
        drawn = [r.node for r in constants(graphs[q.graph], kind, n).collect()] if kind else [None] * n
        out += [(f"{q.id}.{k}", q.graph, c if q.s else None, q.path, c if q.o else None) for k, c in enumerate(drawn)]
    return out


METHODS = ("core", "frontier", "ring", "product", "operators", "per node")


def _run(g: Graph, method: str, s: str | None, path: str, o: str | None, options: RpqOptions) -> int:
    from ..baselines import alp, pernode, product

    if method in ("core", "frontier", "ring"):
        executor = {"core": "auto"}.get(method, method)
        return planner.evaluate(g, path, s, o, dataclasses.replace(options, executor=executor)).count()
    if method == "product":
        return product.evaluate(g, path, s, o).count()
    if method == "per node":
        out = pernode.evaluate(g, path, o=o)
        return (out if s is None else out.filter(F.col("s") == s)).count()
    return alp.evaluate(g, path, s, o).count()


def run(spark, graphs: dict[str, Graph], log: list[tuple], method: str = "core", options: RpqOptions = RpqOptions(limit=1_000_000, timeout_s=60)) -> DataFrame:
    """(query, pattern, method, seconds, answers): one timed run each. A query that its executor
    ends by the time limit has the limit's seconds and no answers."""
    rows = []
    for qid, graph, s, path, o in log:
        began = time.time()
        try:
            n = _run(graphs[graph], method, s, path, o, options)
        except (Timeout, PythonException) as ended:
            # A task that is over the limit ends by an error of its own.
            if isinstance(ended, PythonException) and "the time limit is over" not in str(ended):
                raise
            n = None
        rows.append((qid, patterns.classify(s, path, o), method, time.time() - began, n))
    return spark.createDataFrame(rows, "query string, pattern string, method string, seconds double, answers long")


def answers(graphs: dict[str, Graph], total: int = 200, method: str = "core", options: RpqOptions = RpqOptions()) -> DataFrame:
    """(model, pattern, constant, queries, answers): a whole log, the queries of one model in one
    run that is keyed by their constants; both ends open: one run stands for its queries."""
    from ..baselines import product

    out = None
    for pattern, kind, q, n in models(total):
        g = graphs[q.graph]
        if not kind:
            found = planner.counted(g, q.path, options) if method == "core" else product.evaluate(g, q.path).agg(F.count("*").alias("answers"))
            part = found.select(F.lit(None).cast("string").alias("constant"), F.lit(n).cast("long").alias("queries"), "answers")
        else:
            ends = constants(g, kind, n)
            if method == "core":
                found = keyed.from_each(g, q.path, ends, q.o is None, options)
            else:
                e = parse(q.path) if q.o is None else rewrite.reverse(parse(q.path))
                seen, finals, _ = product.reached(g, e, ends)
                found = seen.filter(F.col("state").isin(*finals)).select("origin", "node").distinct()
            counted = found.groupBy("origin").agg(F.count("*").alias("n"))
            part = ends.join(counted, F.col("node") == F.col("origin"), "left").select(F.col("node").alias("constant"), F.lit(1).cast("long").alias("queries"), F.coalesce("n", F.lit(0)).cast("long").alias("answers"))
        part = part.select(F.lit(q.id).alias("model"), F.lit(pattern).alias("pattern"), "constant", "queries", "answers")
        out = part if out is None else out.unionByName(part)
    return out
