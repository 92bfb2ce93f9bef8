"""Star-free expressions as ordinary joins; set semantics throughout."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import Graph
from ..lang.ast import Alt, Cat, Class, Expr
from ..lang.rewrite import has_at, push_inverse, simplify, star_free_words


def edges_of(g: Graph, c: Class) -> DataFrame:
    """(s, o) of one step over any of the labels of a class."""
    pairs = c.over(g.labels() if c.negated else [])
    parts = []
    for inverse in (False, True):
        names = sorted(n for n, i in pairs if i is inverse)
        if names:
            e = g.edges.filter(F.col("p") == names[0] if len(names) == 1 else F.col("p").isin(names))
            parts.append(e.select(F.col("o").alias("s"), F.col("s").alias("o")) if inverse else e.select("s", "o"))
    if not parts:
        return g.edges.select("s", "o").limit(0)
    out = parts[0] if len(parts) == 1 else parts[0].union(parts[1])
    return out.distinct() if len(pairs) > 1 else out


def single(g: Graph, c: Class) -> DataFrame:
    return edges_of(g, c)


def alternation(g: Graph, classes: list[Class]) -> DataFrame:
    """One scan for all labels, then one removal of duplicates."""
    if all(not c.negated for c in classes):
        return edges_of(g, Class(frozenset().union(*(c.labels for c in classes))))
    out = edges_of(g, classes[0])
    for c in classes[1:]:
        out = out.union(edges_of(g, c))
    return out.distinct()


def _alone(pairs: DataFrame, column: str) -> bool:
    """Whether a column of distinct pairs holds no value twice."""
    return not pairs.groupBy(column).agg(F.count("*").alias("n")).filter("n > 1").limit(1).count()


def concat2(g: Graph, a: Class, b: Class, s: str | None = None, o: str | None = None) -> DataFrame:
    """Both sides are cut to the common middle nodes first, then expanded; a constant end cuts its
    side, and with it the middle, before anything is joined. Pairs are only made distinct where one could be
    found by two middle nodes."""
    left, right = edges_of(g, a).withColumnRenamed("o", "m"), edges_of(g, b).withColumnRenamed("s", "m")
    if s is not None or o is not None:
        left = left if s is None else left.filter(F.col("s") == s)
        right = right if o is None else right.filter(F.col("o") == o)
        return left.join(right, "m").select("s", "o").distinct()
    if _alone(left, "s") or _alone(right, "o"):
        # Each start, or each end, has one middle node: no pair is found twice.
        return left.join(right, "m").select("s", "o")
    middle = left.select("m").distinct().join(right.select("m").distinct(), "m", "left_semi")
    return left.join(middle, "m", "left_semi").join(right.join(middle, "m", "left_semi"), "m").select("s", "o").distinct()


def count2(g: Graph, a: Class, b: Class) -> DataFrame | None:
    """(answers): the number of pairs of two steps, where each start or each end has one middle node, else None."""
    left, right = edges_of(g, a).withColumnRenamed("o", "m"), edges_of(g, b).withColumnRenamed("s", "m")
    if not (_alone(left, "s") or _alone(right, "o")):
        return None
    at = lambda pairs, name: pairs.groupBy("m").agg(F.count("*").alias(name))
    return at(left, "x").join(at(right, "y"), "m").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).alias("answers"))


def fixed_length(g: Graph, words: list[tuple[Class, ...]], distinct: bool = True, starts: DataFrame | None = None, ends: DataFrame | None = None) -> DataFrame | None:
    """Union of join chains, one per word; the empty word relates every node to itself.

    ``starts``, ``ends``: (node), those of the pairs, to which a chain's first and last steps are cut before it is joined."""
    out = None

    def cut(pairs: DataFrame, column: str, nodes: DataFrame | None) -> DataFrame:
        return pairs if nodes is None else pairs.join(nodes.select(F.col("node").alias(column)), column, "left_semi").select("s", "o")

    for w in words:
        if not w:
            part = cut(cut(g.nodes().select(F.col("node").alias("s"), F.col("node").alias("o")), "s", starts), "o", ends)
        else:
            part = cut(edges_of(g, w[0]), "s", starts)
            part = cut(part, "o", ends) if len(w) == 1 else part
            for k, c in enumerate(w[1:]):
                step = cut(edges_of(g, c), "o", ends if k + 2 == len(w) else None).select(F.col("s").alias("_m"), F.col("o").alias("_o"))
                part = part.join(step, part["o"] == step["_m"]).select("s", F.col("_o").alias("o"))
                part = part.distinct() if distinct and k + 2 < len(w) else part
        out = part if out is None else out.union(part)
    return out.distinct() if distinct and out is not None else out


def plan(e: Expr) -> str:
    """Which fast path takes an expression, or none: single, alternation, concat2, words."""
    e = simplify(push_inverse(e))
    if has_at(e):
        return ""
    match e:
        case Class():
            return "single"
        case Alt(parts) if all(isinstance(p, Class) for p in parts):
            return "alternation"
        case Cat((Class(), Class())):
            return "concat2"
    return "words" if star_free_words(e) is not None else ""


def evaluate(g: Graph, e: Expr, s: str | None = None, o: str | None = None) -> DataFrame | None:
    """(s, o) of all answers, or None if the expression has a closure. Constants only save work
    here; the caller filters by them."""
    e = simplify(push_inverse(e))
    match plan(e):
        case "single":
            return single(g, e)
        case "alternation":
            return alternation(g, list(e.parts))
        case "concat2":
            return concat2(g, *e.parts, s, o)
        case "words":
            return fixed_length(g, star_free_words(e))
    return None
