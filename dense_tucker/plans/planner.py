"""From metadata and a strategy to a plan that every sweep reuses."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

from ..model.meta import TensorMeta
from . import grids as G
from . import optimal, trees

#: Named strategies: tree, order of modes, kind of grid.
STRATEGIES = {
    "chain_K": ("chain", "K", "static"),
    "chain_h": ("chain", "h", "static"),
    "balanced": ("balanced", "natural", "static"),
    "opt_static": ("optimal", "natural", "static"),
    "opt_dynamic": ("optimal", "natural", "dynamic"),
}


@dataclass
class Plan:
    meta: TensorMeta
    p: int
    tree: trees.Node
    scheme: G.Scheme
    load: int
    stats: dict = field(default_factory=dict)

    @property
    def volume(self) -> int:
        return self.scheme.total

    @property
    def relative_volume(self) -> float:
        """Volume over the tensor's cardinality: 0 is free of communication."""
        return self.volume / self.meta.cardinality()

    @property
    def input_passes(self) -> int:
        return trees.input_passes(self.tree)

    @property
    def core_load(self) -> int:
        """Flops of the closing chain that makes the core (not part of the tree's load)."""
        order = trees.mode_order(self.meta, "h")
        done = total = 0
        for m in order:
            total += self.meta.K[m] * self.meta.size_after(done)
            done |= 1 << m
        return total

    def rows(self) -> list[dict]:
        return [r | {"grid": list(self.scheme.grids[r["node"]])} for r in trees.annotate(self.tree, self.meta)]

    def explain(self) -> str:
        out = [f"L={self.meta.L} K={self.meta.K} P={self.p} load={self.load} volume={self.volume} (products {self.scheme.ttm}, regrids {self.scheme.regrid})"]
        for r in self.rows():
            name = {"root": "tensor", "leaf": f"factor {r['mode']}"}.get(r["kind"], f"times {r['mode']}")
            out.append("  " * r["depth"] + f"{name} grid={tuple(r['grid'])} out={r['out_size']} flop={r['flop']}")
        return "\n".join(out)

    def to_json(self) -> str:
        def pack(node):
            return [node.kind, node.mode, [pack(c) for c in node.children]]

        return json.dumps({"L": self.meta.L, "K": self.meta.K, "name": self.meta.name, "p": self.p, "tree": pack(self.tree), "grids": {str(k): v for k, v in self.scheme.grids.items()}})

    @classmethod
    def from_json(cls, text: str) -> Plan:
        def unpack(x):
            return trees.Node(x[0], x[1], tuple(unpack(c) for c in x[2]))

        raw = json.loads(text)
        meta, tree = TensorMeta(tuple(raw["L"]), tuple(raw["K"]), raw["name"]), unpack(raw["tree"])
        scheme = G.scheme_volume(tree, meta, {int(k): tuple(v) for k, v in raw["grids"].items()})
        return cls(meta, raw["p"], tree, scheme, trees.tree_load(tree, meta))


def plan(meta: TensorMeta, p: int, tree: str | trees.Node = "optimal", order: str | list[int] = "natural", grid: str | G.Grid = "dynamic", target_rule: str = "full", volume_model: str = "paper", prefer: str = "first", joint: bool = False) -> Plan:
    """Compose any tree (chain, balanced, optimal or one's own) with any gridding (static, dynamic or one's own grid).

    joint: among the heuristic trees and the optimal one, take the least sum of load and volume instead.
    """
    began = time.perf_counter()
    stats: dict = {}
    if joint:
        options = [plan(meta, p, t, o, grid, target_rule, volume_model, prefer) for t, o in (("optimal", "natural"), ("balanced", "natural"), ("balanced", "K"), ("balanced", "h"), ("chain", "K"), ("chain", "h"))]
        return min(options, key=lambda x: (x.load + x.volume, x.load))
    if isinstance(tree, trees.Node):
        made = tree
    elif tree == "optimal":
        made, _, search = optimal.optimal_tree(meta)
        stats = {"dp_states": search.states, "dp_lookups": search.lookups}
    else:
        made = {"chain": trees.chain_tree, "balanced": trees.balanced_tree}[tree](trees.mode_order(meta, order))
    trees.validate_tree(made, meta.n)
    stats["grids_scanned"] = len(G.valid_grids(meta, p))
    if grid == "dynamic":
        scheme = G.best_dynamic_scheme(made, meta, p, target_rule, volume_model, prefer)
    else:
        fixed = G.best_static_grid(made, meta, p, volume_model)[0] if grid == "static" else tuple(grid)
        scheme = G.static_scheme(made, meta, fixed, volume_model)
    stats["planner_s"] = time.perf_counter() - began
    return Plan(meta, p, made, scheme, trees.tree_load(made, meta), stats)


def strategy(meta: TensorMeta, p: int, name: str) -> Plan:
    tree, order, grid = STRATEGIES[name]
    return plan(meta, p, tree, order, grid)


def plan_seq_init(meta: TensorMeta, p: int) -> tuple[list[int], G.Scheme]:
    """Order of modes for sequentially truncated initialisation, and grids along its one chain."""
    order, _ = optimal.seq_init_order(meta)
    line = trees.root(*trees.chain(order[:-1], (trees.leaf(order[-1]),)))
    return order, G.best_dynamic_scheme(line, meta, p)
