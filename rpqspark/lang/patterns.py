"""Patterns of queries: end kinds and operators, names erased."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ast import Alt, At, Cat, Class, Eps, Expr, Inv, Opt, Plus, Star
from .parser import PathError, parse


def operators(e: Expr) -> str:
    match e:
        case Eps() | At():
            return ""
        case Class(labels, negated):
            return ("!" if negated else "") + "|".join("^" if i else "" for _, i in sorted(labels, key=lambda x: x[1]))
        case Cat(p):
            return "/".join(map(operators, p))
        case Alt(p):
            return "|".join(map(operators, p))
        case Star(b):
            return operators(b) + "*"
        case Plus(b):
            return operators(b) + "+"
        case Opt(b):
            return operators(b) + "?"
        case Inv(b):
            return "^" + operators(b)
    raise TypeError(e)


def is_variable(term: str | None) -> bool:
    return term is None or term.startswith("?")


def classify(s: str | None, e: Expr | str, o: str | None) -> str:
    """Such as ``v /* c``: a variable, a concatenation, a star, a constant."""
    e = parse(e) if isinstance(e, str) else e
    end = lambda t: "v" if is_variable(t) else "c"
    return " ".join(x for x in (end(s), operators(e), end(o)) if x)


def pattern_histogram(queries: DataFrame) -> DataFrame:
    """(pattern, n) of a table of queries (s, path, o); each path is parsed once for each kind of ends."""
    label = F.udf(lambda s, p, o: classify(s, p, o), useArrow=True)
    kind = lambda c: F.when(F.col(c).isNotNull() & ~F.col(c).startswith("?"), F.lit("constant")).alias(c)
    kinds = queries.select(kind("s"), "path", kind("o")).groupBy("s", "path", "o").agg(F.count("*").alias("n"))
    return kinds.select(label("s", "path", "o").alias("pattern"), "n").groupBy("pattern").agg(F.sum("n").alias("n"))


def trivial(path: str) -> bool:
    """One forward label: an ordinary triple pattern."""
    try:
        e = parse(path)
    except PathError:
        return True
    return isinstance(e, Class) and not e.negated and len(e.labels) == 1 and not next(iter(e.labels))[1]
