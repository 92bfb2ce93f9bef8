"""Deterministic automaton by the powerset construction over the labels of an expression."""

from __future__ import annotations

from ..lang.ast import Class
from .epsilon import NFA


def build(nfa: NFA, names) -> NFA:
    """One state per reachable set; a move per (name, inverse) of the given label names."""
    nfa = nfa.without_empty()
    labels = sorted({s for _, c, _ in nfa.moves for s in c.over(names)})
    start = frozenset({nfa.start})
    ids, todo, moves = {start: 0}, [start], []
    while todo:
        now = todo.pop()
        for name, inverse in labels:
            to = frozenset(b for a, c, b in nfa.moves if a in now and c.holds(name, inverse))
            if to:
                if to not in ids:
                    ids[to] = len(ids)
                    todo.append(to)
                moves.append((ids[now], Class(frozenset({(name, inverse)})), ids[to]))
    return NFA(0, {i for s, i in ids.items() if s & nfa.finals}, moves, len(ids))
