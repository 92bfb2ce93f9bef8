"""Position automaton: one state per symbol occurrence and an initial state.

There are no empty transitions, and all transitions into a state carry the labels of
its position. State 0 is the initial one and sits on the highest bit.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from ..lang.ast import Alt, At, Cat, Class, Eps, Expr, Opt, Plus, Star
from ..lang.rewrite import push_inverse


@dataclass
class PositionNFA:
    positions: list[Class]
    nullable: bool
    first: set[int]
    last: set[int]
    follow: dict[int, set[int]]
    #: Nodes that must be where a state is entered, from must-pass nodes in the expression.
    arrive: dict[int, str] = field(default_factory=dict)

    @property
    def m(self) -> int:
        return len(self.positions)

    def bit(self, state: int) -> int:
        return 1 << (self.m - state)

    def mask(self, states) -> int:
        return sum(self.bit(q) for q in states)

    @property
    def initial(self) -> int:
        return self.bit(0)

    @property
    def final(self) -> int:
        return self.mask(self.last) | (self.initial if self.nullable else 0)

    def after(self, state: int) -> set[int]:
        return self.first if state == 0 else self.follow[state]

    def targets(self, name: str, inverse: bool) -> set[int]:
        return {q for q, c in enumerate(self.positions, 1) if c.holds(name, inverse)}

    def step(self, states: set[int], name: str, inverse: bool = False) -> set[int]:
        """Successors by a label: successors by anything, cut with the label's targets."""
        return set().union(*(self.after(q) for q in states)) & self.targets(name, inverse)

    def accepts(self, word: list[tuple[str, bool]]) -> bool:
        now = {0}
        for name, inverse in word:
            now = self.step(now, name, inverse)
        return bool(now & self.last) or (self.nullable and 0 in now)


def build(e: Expr) -> PositionNFA:
    nfa = PositionNFA([], False, set(), set(), {})

    def walk(x: Expr) -> tuple[bool, set[int], set[int]]:
        match x:
            case Eps():
                return True, set(), set()
            case Class():
                nfa.positions.append(x)
                q = len(nfa.positions)
                nfa.follow[q] = set()
                return False, {q}, {q}
            case Cat(parts):
                null, first, last = True, set(), set()
                pinned = None
                for p in parts:
                    if isinstance(p, At):
                        if not last:
                            raise ValueError("a must-pass node needs a step before it; use the start term instead")
                        if null:
                            raise ValueError("a must-pass node needs a step before it that is not optional")
                        for q in last:
                            if nfa.arrive.setdefault(q, p.node) != p.node:
                                raise ValueError("two must-pass nodes in one place")
                        pinned = last
                        continue
                    n, f, l = walk(p)
                    for q in last:
                        nfa.follow[q] |= f
                    if null:
                        first |= f
                    last = (last | l) if n else l
                    null = null and n
                del pinned
                return null, first, last
            case Alt(parts):
                got = [walk(p) for p in parts]
                return any(g[0] for g in got), set().union(*(g[1] for g in got)), set().union(*(g[2] for g in got))
            case Star(b) | Plus(b) | Opt(b):
                n, f, l = walk(b)
                if not isinstance(x, Opt):
                    for q in l:
                        nfa.follow[q] |= f
                return n or not isinstance(x, Plus), f, l
        raise TypeError(x)

    nfa.nullable, nfa.first, nfa.last = walk(push_inverse(e))
    return nfa
