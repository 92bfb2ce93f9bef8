"""Paths of fixed length as graph patterns, with bag semantics until the end."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..exec.fastpaths import fixed_length
from ..graph.model import Graph
from ..lang.parser import parse
from ..lang.rewrite import push_inverse, star_free_words


def evaluate(g: Graph, path: str, bag: bool = True) -> DataFrame:
    """(s, o); with ``bag``, one row per matching path."""
    words = star_free_words(push_inverse(parse(path)))
    if words is None:
        raise ValueError("the path has a closure")
    return fixed_length(g, words, distinct=not bag)
