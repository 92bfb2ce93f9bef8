"""``rpq(...)`` inside SQL text.

A call names a registered graph view and a path, and optional ends:
``SELECT * FROM rpq(graph => 'trade', path => 'placed_by/lives_in', o => 'nation:3')``.
Calls are planned on the driver and replaced by views; ``WHERE`` equalities of the form
``alias.s = '...'`` on an open end move into the call.
"""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..exec import planner
from ..exec.options import RpqOptions
from ..graph.model import Graph

_CALL = re.compile(r"\brpq\s*\(((?:[^()']|'(?:[^']|'')*')*)\)(?:\s+(?:AS\s+)?(?!(?:WHERE|JOIN|ON|GROUP|ORDER|LIMIT|UNION|CROSS|LEFT|INNER)\b)(\w+))?", re.I)
_ARG = re.compile(r"(\w+)\s*=>\s*(?:'((?:[^']|'')*)'|(NULL))", re.I)


def _own_level(text: str) -> str:
    """The rest of the query that a call stands in: text up to the end of that query, with
    what stands in brackets (subqueries, arguments) left out."""
    out, depth, at = [], 0, 0
    while at < len(text):
        c = text[at]
        if c == "'":
            end = re.compile(r"'(?:[^']|'')*'").match(text, at)
            stop = end.end() if end else len(text)
            if not depth:
                out.append(text[at:stop])
            at = stop
            continue
        if c == "(":
            depth += 1
            out.append(" ( " if depth == 1 else "")
        elif c == ")":
            depth -= 1
            if depth < 0:
                break
            out.append(" ) " if not depth else "")
        elif not depth:
            out.append(c)
        at += 1
    return "".join(out)


def _bound(text: str, alias: str | None, column: str) -> str | None:
    """A constant that the query around a call demands of an end, if that is plain to see: a
    conjunct ``alias.column = '...'`` of its own WHERE. Without an alias the call must be
    all that the query reads, else the column may be another table's."""
    own = _own_level(text)
    if re.search(r"\b(OR|NOT|UNION|INTERSECT|EXCEPT|MINUS|CASE|BETWEEN)\b", own, re.I):
        return None
    before, where, after = re.split(r"\b(WHERE)\b", own, maxsplit=1, flags=re.I) if re.search(r"\bWHERE\b", own, re.I) else (own, "", "")
    if not where or not alias and (re.search(r"\bJOIN\b", before, re.I) or "," in before):
        return None
    name = rf"{re.escape(alias)}\.{column}" if alias else column
    for part in re.split(r"\bAND\b", re.split(r"\b(?:GROUP|ORDER|HAVING|LIMIT|SORT|CLUSTER|DISTRIBUTE|WINDOW|OFFSET)\b", after, maxsplit=1, flags=re.I)[0], flags=re.I):
        m = re.fullmatch(rf"\s*{name}\s*=\s*'((?:[^']|'')*)'\s*;?\s*", part, re.I)
        if m:
            return m[1].replace("''", "'")
    return None


def sql(spark: SparkSession, text: str, options: RpqOptions = RpqOptions()) -> DataFrame:
    calls = list(_CALL.finditer(text))

    def replaced(m: re.Match) -> str:
        given = {k.lower(): None if null else v.replace("''", "'") for k, v, null in _ARG.findall(m[1])}
        unknown = set(given) - {"graph", "path", "s", "o"}
        if unknown or not {"graph", "path"} <= set(given):
            raise ValueError(f"rpq takes graph, path, s, o; given {sorted(given)}")
        g = Graph(spark.table(given["graph"]))
        s, o = given.get("s"), given.get("o")
        # Sideways: only where one call stands, so that a column is not ambiguous.
        fixed = {c: _bound(text[m.end():], m[2], c) for c, v in (("s", s), ("o", o)) if v is None} if len(calls) == 1 else {}
        out = planner.evaluate(g, given["path"], s or fixed.get("s"), o or fixed.get("o"), options)
        if s is None and o is None and fixed.get("s") and fixed.get("o"):
            out = out.filter("found").select(F.lit(fixed["s"]).alias("s"), F.lit(fixed["o"]).alias("o"))
        else:
            for c in ("s", "o"):
                if fixed.get(c):
                    out = out.withColumn(c, F.lit(fixed[c]))
        if out.columns != ["found"]:
            out = out.select(*[c for c in ("s", "o") if c in out.columns])
        name = f"rpq_{uuid.uuid4().hex}"
        out.createOrReplaceTempView(name)
        return f"{name} AS {m[2]}" if m[2] else name

    return spark.sql(_CALL.sub(replaced, text))
