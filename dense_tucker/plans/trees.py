"""Trees of tensor-times-matrix products: types, checks, the heuristic trees and their costs.

A node's label is a mode (inner node) or the mode whose new factor is made (leaf). The root bears the tensor.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

from ..model.meta import TensorMeta


@dataclass(frozen=True)
class Node:
    kind: str  # root, mode or leaf
    mode: int  # -1 at the root
    children: tuple[Node, ...] = ()

    def walk(self) -> Iterator[tuple[int, int, int, int, Node]]:
        """(number, parent's number, depth, modes multiplied above as a bit mask, node), depth first."""
        stack, number = [(self, -1, 0, 0)], 0
        while stack:
            node, parent, depth, above = stack.pop()
            yield number, parent, depth, above, node
            below = above | (1 << node.mode if node.kind == "mode" else 0)
            stack += [(c, number, depth + 1, below) for c in reversed(node.children)]
            number += 1


def leaf(mode: int) -> Node:
    return Node("leaf", mode)


def chain(modes: list[int], ends: tuple[Node, ...]) -> tuple[Node, ...]:
    """Hang `ends` under a chain of products."""
    for m in reversed(modes):
        ends = (Node("mode", m, ends),)
    return ends


def root(*children: Node) -> Node:
    return Node("root", -1, tuple(children))


def mode_order(meta: TensorMeta, by: str | list[int] | tuple[int, ...] = "natural") -> list[int]:
    """natural, K (rising core length), h (rising compression factor) or a permutation; ties by mode."""
    if not isinstance(by, str):
        if sorted(by) != list(range(meta.n)):
            raise ValueError("not a permutation of the modes")
        return list(by)
    keys = {"natural": lambda i: i, "K": lambda i: meta.K[i], "h": meta.h}
    return sorted(range(meta.n), key=lambda i: (keys[by](i), i))


def chain_tree(order: list[int]) -> Node:
    """One independent chain for each new factor, each in the given order of modes."""
    return root(*[c for n in order for c in chain([m for m in order if m != n], (leaf(n),))])


def balanced_tree(order: list[int]) -> Node:
    """Halve the modes again and again; each half is multiplied once for all factors of the other half."""

    def under(group: list[int]) -> tuple[Node, ...]:
        if len(group) == 1:
            return (leaf(group[0]),)
        cut = len(group) // 2
        one, two = group[:cut], group[cut:]
        return chain(one, under(two)) + chain(two, under(one))

    return root(*under(list(order)))


def validate_tree(tree: Node, n: int) -> None:
    """Raise ValueError unless tree has the four properties of a product tree over n modes."""
    if tree.kind != "root":
        raise ValueError("the root must bear the tensor")
    leaves = []
    for number, _, _, above, node in tree.walk():
        if number and node.kind == "root":
            raise ValueError("a second root")
        if node.kind == "mode":
            if not 0 <= node.mode < n or above >> node.mode & 1:
                raise ValueError(f"mode {node.mode} is out of range or repeated on a path")
            if not node.children:
                raise ValueError("a product that leads to no factor")
        if node.kind == "leaf":
            if node.children:
                raise ValueError("a leaf with children")
            if above != ((1 << n) - 1) & ~(1 << node.mode):
                raise ValueError(f"the path to factor {node.mode} does not hold all other modes once")
            leaves.append(node.mode)
    if sorted(leaves) != list(range(n)):
        raise ValueError("each factor needs exactly one leaf")


def validate_partial(node: Node, P: int, Q: int, n: int) -> None:
    """The same for a tree below a partly multiplied tensor: P is done, factors of Q are wanted (bit masks)."""
    wanted = []
    for _, _, _, above, x in node.walk():
        if x.kind == "mode" and (P | above) >> x.mode & 1:
            raise ValueError("a mode is multiplied twice")
        if x.kind == "leaf":
            if P | above != ((1 << n) - 1) & ~(1 << x.mode):
                raise ValueError("a path misses a mode")
            wanted.append(x.mode)
    if sorted(wanted) != [i for i in range(n) if Q >> i & 1]:
        raise ValueError("the leaves are not those asked for")


def partial_load(node: Node, P: int, meta: TensorMeta) -> int:
    """Flops of all products of a partial tree."""
    return sum(meta.K[x.mode] * meta.size_after(P | above) for _, _, _, above, x in node.walk() if x.kind == "mode")


def annotate(tree: Node, meta: TensorMeta) -> list[dict]:
    """One row for each node: number, parent, depth, kind, mode (from 1), in and out cardinality, flops."""
    rows = []
    for number, parent, depth, above, node in tree.walk():
        size = meta.size_after(above)
        out = meta.size_after(above | 1 << node.mode) if node.kind == "mode" else size
        rows.append({"node": number, "parent": parent, "depth": depth, "kind": node.kind, "mode": node.mode + 1, "in_size": size, "out_size": out, "flop": meta.K[node.mode] * size if node.kind == "mode" else 0})
    return rows


def tree_load(tree: Node, meta: TensorMeta, normalised: bool = False):
    """Flops of all products; normalised: over the tensor's cardinality."""
    total = partial_load(tree, 0, meta)
    return total / meta.cardinality() if normalised else total


def ttm_count(tree: Node) -> int:
    return sum(node.kind == "mode" for _, _, _, _, node in tree.walk())


def input_passes(tree: Node) -> int:
    """How often the tensor itself is read."""
    return len(tree.children)


def classify(tree: Node, n: int) -> dict[int, tuple[int, int, int]]:
    """For each inner node its sets as bit masks: multiplied so far (itself included), made below, the rest."""
    made: dict[int, int] = {}
    walked = list(tree.walk())
    for number, parent, _, _, node in reversed(walked):
        own = made.get(number, 0) | (1 << node.mode if node.kind == "leaf" else 0)
        made[number] = own
        made[parent] = made.get(parent, 0) | own
    full = (1 << n) - 1
    return {number: (above | 1 << node.mode, made[number], full & ~(above | 1 << node.mode | made[number])) for number, _, _, above, node in walked if node.kind == "mode"}


def _without(node: Node, mode: int) -> tuple[Node, ...]:
    """The node without products along a mode; children of a removed one take its place."""
    below = tuple(x for c in node.children for x in _without(c, mode))
    return below if node.kind == "mode" and node.mode == mode else (replace(node, children=below),)


def _leaves(node: Node) -> set[int]:
    return {x.mode for _, _, _, _, x in node.walk() if x.kind == "leaf"}


def binarise(tree: Node) -> Node:
    """An equally valid tree with at most two children at every node and no greater load.

    Of three children, one whose mode's factor is made under another takes in the third, which then needs
    no product along that mode any more; children with the same mode become one.
    """

    def fix(node: Node) -> Node:
        kids = list(node.children)
        merged = True
        while merged:
            merged = False
            for i, a in enumerate(kids):
                for j in range(i + 1, len(kids)):
                    b = kids[j]
                    if a.kind == b.kind == "mode" and a.mode == b.mode:
                        kids[i] = replace(a, children=a.children + b.children)
                        del kids[j]
                        merged = True
                        break
                if merged:
                    break
            if not merged and len(kids) > 2:
                for i, a in enumerate(kids):
                    if a.kind != "mode":
                        continue
                    others = [j for j in range(len(kids)) if j != i and kids[j].kind == "mode" and a.mode not in _leaves(kids[j])]
                    if others:
                        j = others[0]
                        kids[i] = replace(a, children=a.children + _without(kids[j], a.mode))
                        del kids[j]
                        merged = True
                        break
        return replace(node, children=tuple(fix(c) for c in kids))

    return fix(tree)


def execution_schedule(tree: Node) -> list[tuple[str, int]]:
    """Depth-first trace of ('make' | 'drop', node number): an output is dropped once its last child has run."""
    rows = {number: (parent, node) for number, parent, _, _, node in tree.walk()}
    left = {number: len(node.children) for number, (_, node) in rows.items()}
    trace: list[tuple[str, int]] = []
    for number, (parent, node) in rows.items():
        if node.kind == "mode":
            trace.append(("make", number))
        done = number if node.kind == "leaf" else None
        while done is not None:
            up = rows[done][0]
            if done != number:
                trace.append(("drop", done))
            if up < 0:
                break
            left[up] -= 1
            done = up if left[up] == 0 and rows[up][1].kind == "mode" else None
    return trace


def peak_live_tensors(schedule: list[tuple[str, int]]) -> int:
    live = most = 0
    for what, _ in schedule:
        live += 1 if what == "make" else -1
        most = max(most, live)
    return most


def depth(tree: Node) -> int:
    """Products on the longest path."""
    return max(d for _, _, d, _, node in tree.walk() if node.kind != "leaf")
