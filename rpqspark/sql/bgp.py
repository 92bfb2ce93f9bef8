"""Basic graph patterns whose predicates may be paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..exec import fastpaths, keyed, planner
from ..exec.options import RpqOptions
from ..graph.model import Graph
from ..lang.parser import parse
from ..lang.patterns import is_variable
from ..lang.rewrite import push_inverse, simplify, star_free_words


def evaluate(g: Graph, patterns: list[tuple[str, str, str]], options: RpqOptions = RpqOptions()) -> DataFrame:
    """Bindings (one column per variable, without ?) of all patterns (s, path, o).

    Join-only patterns go first. A path with a closure is evaluated for the
    distinct bindings that its ends already have, not for all nodes; so is a join-only one that reads
    more than ``options.kernel_edges`` edges. All variables are kept, so joined sets stay sets.
    """
    plain = [p for p in patterns if fastpaths.plan(parse(p[1]))]
    hard = [p for p in patterns if p not in plain]
    out: DataFrame | None = None

    def join(out, part):
        if out is None:
            return part
        shared = [c for c in part.columns if c in out.columns]
        return out.join(part, shared) if shared else out.crossJoin(part)

    def named(df, s, o):
        if s == o and is_variable(s):
            # One variable at both ends: pairs that close, or their one column already.
            df = df.filter("s = o") if "o" in df.columns else df
            return df.select(F.col("s").alias(s[1:])).distinct()
        return df.select(*[F.col(c).alias(t[1:]) for c, t in (("s", s), ("o", o)) if is_variable(t)])

    for s, path, o in plain + hard:
        bound = [t[1:] for t in (s, o) if is_variable(t) and out is not None and t[1:] in out.columns]
        if (s, path, o) in plain or not bound or not (is_variable(s) and is_variable(o)):
            got = _cut_to_bound(g, path, out, s, o, bound, options) if len(bound) and is_variable(s) and is_variable(o) and _large(g, path, options) else planner.evaluate(g, path, s, o, options)
            part = got.filter("found").select() if got.columns == ["found"] else named(got, s, o)
        else:
            part = named(_from_bound(g, path, out, s, o, bound[0] == s[1:], options), s, o)
        out = join(out, part)
    return out


def _large(g: Graph, path: str, options: RpqOptions) -> bool:
    """Whether a stored graph has more edges of a join-only path's labels than the kernel would take."""
    return g.is_stored and bool(fastpaths.plan(parse(path))) and sum(g.counts().get(n, 0) for n in planner.plan(g, path).labels) > options.kernel_edges


def _cut_to_bound(g: Graph, path: str, out: DataFrame, s: str, o: str, bound: list[str], options: RpqOptions) -> DataFrame:
    """(s, o) pairs of a join-only path whose bound ends are among the bindings."""
    only = lambda t: out.select(F.col(t[1:]).alias("node")).distinct() if t[1:] in bound else None
    return fastpaths.fixed_length(g, star_free_words(simplify(push_inverse(parse(path)))), starts=only(s), ends=only(o))


def _from_bound(g: Graph, path: str, out: DataFrame, s: str, o: str, forward: bool, options: RpqOptions) -> DataFrame:
    """(s, o) pairs whose one end is bound already."""
    found = keyed.from_each(g, path, out.select(F.col((s if forward else o)[1:]).alias("node")), forward, options)
    a, b = ("s", "o") if forward else ("o", "s")
    return found.select(F.col("origin").alias(a), F.col("node").alias(b))
