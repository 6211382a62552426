"""The product tree of least load, by dynamic programming over partial trees; and brute force to check it.

A state is a pair of bit masks: modes multiplied so far and factors still to be made. All other modes can be
multiplied once for all of these factors (reuse), or the factors are made in two groups (split); a group may
then also multiply the modes of the other one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cache
from math import factorial

from ..model.meta import TensorMeta
from .trees import Node, leaf, partial_load, root


@dataclass
class Stats:
    states: int = 0
    lookups: int = 0


@dataclass
class Search:
    """policy: dp (both choices), always_reuse (greedy where possible) or no_reuse (split down to single factors)."""

    meta: TensorMeta
    policy: str = "dp"
    stats: Stats = field(default_factory=Stats)
    best: dict[tuple[int, int], tuple[int, tuple]] = field(default_factory=dict)

    def _choices(self, P: int, Q: int) -> Iterator[tuple]:
        full = (1 << self.meta.n) - 1
        R = full & ~(P | Q)
        single = Q & (Q - 1) == 0
        reuse_ok = R and (self.policy != "no_reuse" or single)
        if reuse_ok:
            for m in range(self.meta.n):
                if R >> m & 1:
                    yield ("reuse", m)
        if not single and not (reuse_ok and self.policy == "always_reuse"):
            low = Q & -Q
            part = (Q - 1) & Q
            while part:
                if part & low:
                    yield ("split", part)
                part = (part - 1) & Q

    def _parts(self, P: int, Q: int, choice: tuple) -> list[tuple[int, int]]:
        if choice[0] == "reuse":
            return [(P | 1 << choice[1], Q)]
        return [(P, choice[1]), (P, Q & ~choice[1])]

    def solve(self, P: int, Q: int) -> int:
        """Least cost of a state; explicit stack instead of recursion."""
        stack = [(P, Q)]
        full = (1 << self.meta.n) - 1
        while stack:
            state = stack[-1]
            if state in self.best:
                stack.pop()
                continue
            p, q = state
            if p | q == full and q & (q - 1) == 0:
                self.best[state] = (0, ())
                self.stats.states += 1
                stack.pop()
                continue
            options = [(c, self._parts(p, q, c)) for c in self._choices(p, q)]
            missing = [s for _, parts in options for s in parts if s not in self.best]
            if missing:
                stack += missing
                continue
            found = None
            for c, parts in options:
                self.stats.lookups += 1
                cost = sum(self.best[s][0] for s in parts) + (self.meta.K[c[1]] * self.meta.size_after(p) if c[0] == "reuse" else 0)
                if found is None or cost < found[0]:
                    found = (cost, c)
            self.best[state] = found
            self.stats.states += 1
            stack.pop()
        return self.best[P, Q][0]

    def nodes(self, P: int, Q: int) -> tuple[Node, ...]:
        """Children of the node at this state in a best tree."""
        choice = self.best[P, Q][1]
        if not choice:
            return (leaf(Q.bit_length() - 1),)
        if choice[0] == "reuse":
            return (Node("mode", choice[1], self.nodes(P | 1 << choice[1], Q)),)
        return tuple(x for s in self._parts(P, Q, choice) for x in self.nodes(*s))


def optimal_tree(meta: TensorMeta, policy: str = "dp") -> tuple[Node, int, Stats]:
    """Tree of least load, its load and the search's size."""
    search = Search(meta, policy)
    full = (1 << meta.n) - 1
    load = search.solve(0, full)
    return root(*search.nodes(0, full)), load, search.stats


def enumerate_trees(n: int) -> list[Node]:
    """All trees that reuse and split can build (n up to 4)."""
    full = (1 << n) - 1

    @cache
    def below(P: int, Q: int) -> tuple[tuple[Node, ...], ...]:
        if P | Q == full and Q & (Q - 1) == 0:
            return ((leaf(Q.bit_length() - 1),),)
        out: list[tuple[Node, ...]] = []
        for m in range(n):
            if not (P | Q) >> m & 1:
                out += [(Node("mode", m, kids),) for kids in below(P | 1 << m, Q)]
        low, part = Q & -Q, (Q - 1) & Q
        while part:
            if part & low:
                out += [a + b for a in below(P, part) for b in below(P, Q & ~part)]
            part = (part - 1) & Q
        return tuple(out)

    return [root(*kids) for kids in below(0, full)]


def brute_force_load(meta: TensorMeta) -> int:
    return min(partial_load(t, 0, meta) for t in enumerate_trees(meta.n))


def naive_scheme_count(n: int) -> int:
    """Ways to order n separate chains."""
    return factorial(n - 1) ** n


def seq_init_order(meta: TensorMeta) -> tuple[list[int], int]:
    """Order of modes of least work for sequentially truncated initialisation: Gram plus product on what is left."""
    full = (1 << meta.n) - 1
    best: dict[int, tuple[int, list[int]]] = {0: (0, [])}
    for done in range(full + 1):
        if done not in best:
            continue
        cost, order = best[done]
        size = meta.size_after(done)
        for m in range(meta.n):
            if not done >> m & 1:
                new = (cost + size * (meta.L[m] + meta.K[m]), [*order, m])
                key = done | 1 << m
                if key not in best or new < best[key]:
                    best[key] = new
    return best[full][1], best[full][0]
