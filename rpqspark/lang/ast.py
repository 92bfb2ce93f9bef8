"""Syntax tree of path expressions. A position holds a set of labels, so negated
and class labels cost one position."""

from __future__ import annotations

from dataclasses import dataclass


class Expr:
    pass


@dataclass(frozen=True)
class Eps(Expr):
    pass


@dataclass(frozen=True)
class Class(Expr):
    """One step over any of ``labels``, pairs (name, inverse); negated: over any other
    label in the directions that occur in the set."""

    labels: frozenset
    negated: bool = False

    def holds(self, name: str, inverse: bool) -> bool:
        if not self.negated:
            return (name, inverse) in self.labels
        return inverse in {i for _, i in self.labels} and (name, inverse) not in self.labels

    def over(self, names) -> set:
        """The (name, inverse) pairs it matches, given all label names of a graph."""
        if not self.negated:
            return set(self.labels)
        return {(n, i) for i in {i for _, i in self.labels} for n in names} - self.labels


@dataclass(frozen=True)
class At(Expr):
    """The path passes this node here."""

    node: str


@dataclass(frozen=True)
class Cat(Expr):
    parts: tuple


@dataclass(frozen=True)
class Alt(Expr):
    parts: tuple


@dataclass(frozen=True)
class Star(Expr):
    body: Expr


@dataclass(frozen=True)
class Plus(Expr):
    body: Expr


@dataclass(frozen=True)
class Opt(Expr):
    body: Expr


@dataclass(frozen=True)
class Inv(Expr):
    body: Expr


def sym(name: str, inverse: bool = False) -> Class:
    return Class(frozenset({(name, inverse)}))


def text(e: Expr) -> str:
    """The expression as text that parses back to it."""

    def atom(x):
        return text(x) if isinstance(x, (Class, Eps, At, Star, Plus, Opt)) or isinstance(x, Inv) else f"({text(x)})"

    def name(n, i):
        import re

        return ("^" if i else "") + (n if re.fullmatch(r"[\w#:.\-]+", n) else "'" + n + "'")

    match e:
        case Eps():
            return "()"
        case At(node):
            return "@" + name(node, False)
        case Class(labels, negated):
            inner = "|".join(name(*x) for x in sorted(labels))
            return f"!({inner})" if negated else inner if len(labels) == 1 else f"[{inner}]"
        case Cat(parts):
            return "/".join(f"({text(p)})" if isinstance(p, (Alt, Cat)) else text(p) for p in parts)
        case Alt(parts):
            return "|".join(f"({text(p)})" if isinstance(p, Alt) else text(p) for p in parts)
        case Star(b) | Plus(b) | Opt(b):
            inner = f"({text(b)})" if isinstance(b, (Inv,)) else atom(b)
            return inner + {Star: "*", Plus: "+", Opt: "?"}[type(e)]
        case Inv(b):
            return f"^({text(b)})"
    raise TypeError(e)
