"""A model whose pairs form a forest, evaluated by messages along it instead of terms.

Summing attributes out along the forest costs the sizes of the pair tables and has no alternating terms, so
it stays stable and cheap where inclusion and exclusion would need too many groups.
"""

from __future__ import annotations

import numpy as np

from probsum.plans.model import Family, Model, TooManyTerms


class ForestModel(Model):
    """Same interface as Model; rectangles must be over pairs, and the pairs acyclic."""

    def __init__(self, values, families=(), n=None):
        super().__init__(values, [], n)
        self.families = list(families)
        self.delta = [np.where(f.targets > 0, 1.0, 0.0) for f in self.families]
        self._check()
        if any(len(f.attrs) != 2 for f in self.families):
            raise ValueError("rectangles must be over pairs")
        self.edges = [tuple(f.attrs) for f in self.families]
        self.components, self.free = [], list(self.attrs)
        self._orders = self._trees()

    def _trees(self) -> list[list[tuple[str, int | None]]]:
        """Attributes of every tree from the root down, each with the family that leads to it."""
        seen: set[str] = set()
        trees = []
        for root in self.attrs:
            if root in seen:
                continue
            seen.add(root)
            order, used = [(root, None)], set()
            for a, _ in order:
                for f, (x, y) in enumerate(self.edges):
                    if f in used or a not in (x, y):
                        continue
                    used.add(f)
                    b = y if a == x else x
                    if b in seen:
                        raise ValueError("the pairs form a cycle")
                    seen.add(b)
                    order.append((b, f))
            trees.append(order)
        return trees

    def _table(self, f: int, first: str) -> np.ndarray:
        """1 outside the rectangles, their variables inside; rows are values of `first`."""
        fam = self.families[f]
        a, b = fam.attrs
        t = np.ones((self.sizes[a], self.sizes[b]))
        for r in range(fam.size):
            t[np.ix_(fam.masks[a][r], fam.masks[b][r])] = self.delta[f][r]
        return t if first == a else t.T

    def _messages(self, weights):
        """(values per tree, incoming products per attribute without its own variables, messages per family)."""
        node = {a: self.alpha[a] * weights[a] if a in weights else self.alpha[a] for a in self.attrs}
        inward: dict[str, np.ndarray] = {a: np.ones(self.sizes[a]) for a in self.attrs}
        up: dict[int, np.ndarray] = {}
        parent = {b: a for order in self._orders for b, f in order if f is not None for a in self.edges[f] if a != b}
        totals = []
        for order in self._orders:
            for b, f in reversed(order):
                if f is not None:
                    a = parent[b]
                    up[f] = self._table(f, a) @ (node[b] * inward[b])
                    inward[a] = inward[a] * up[f]
            root = order[0][0]
            totals.append(float(node[root] @ inward[root]))
        return node, inward, up, parent, totals

    def _full(self, weights):
        """inward products with the messages from the parents' side added."""
        node, inward, up, parent, totals = self._messages(weights)
        outer = dict(inward)
        down: dict[int, np.ndarray] = {}
        for order in self._orders:
            for b, f in order[1:]:
                a = parent[b]
                with np.errstate(divide="ignore", invalid="ignore"):
                    rest = np.where(up[f] > 0, outer[a] / up[f], 0.0)
                if (up[f] == 0).any():  # the product without this message, from its other factors
                    rest = np.ones(self.sizes[a])
                    for c, g in order[1:]:
                        if parent[c] == a and g != f:
                            rest = rest * up[g]
                    lead = next((g for x, g in order if x == a), None)
                    if lead is not None:
                        rest = rest * down[lead]
                down[f] = self._table(f, a).T @ (node[a] * rest)
                outer[b] = inward[b] * down[f]
                down[f, "rest"] = rest
        return node, inward, outer, down, parent, totals

    def evaluate(self, weights=None) -> float:
        return float(np.prod(self._messages(weights or {})[4]))

    def partial_values(self, attr, weights=None) -> np.ndarray:
        weights = {k: v for k, v in (weights or {}).items() if k != attr}
        _, _, outer, _, _, totals = self._full(weights)
        i = next(i for i, order in enumerate(self._orders) if any(a == attr for a, _ in order))
        return outer[attr] * float(np.prod([t for j, t in enumerate(totals) if j != i]))

    def partial_rects(self, f: int) -> tuple[np.ndarray, float]:
        node, inward, _, down, parent, totals = self._full({})
        i = next(i for i, order in enumerate(self._orders) if any(g == f for _, g in order))
        b = next(b for b, g in self._orders[i] if g == f)
        a = parent[b]
        base = float(np.prod([t for j, t in enumerate(totals) if j != i]))
        left, right = node[a] * down[f, "rest"], node[b] * inward[b]
        fam = self.families[f]
        q = np.einsum("ra,rb->r", fam.masks[a] * left, fam.masks[b] * right)
        p0 = left.sum() * right.sum() - q.sum()
        return q * base, max(float(p0) * base, 0.0)

    def groups2(self, a: str, b: str, weights) -> np.ndarray:
        """Unscaled counts of all groups of two attributes, one pass per value of the smaller domain."""
        if self.sizes[a] > self.sizes[b]:
            return self.groups2(b, a, weights).T
        out = np.zeros((self.sizes[a], self.sizes[b]))
        for x in range(self.sizes[a]):
            pick = np.zeros(self.sizes[a])
            pick[x] = 1.0
            w = {**weights, a: pick * weights.get(a, 1.0)}
            out[x] = self.alpha[b] * w.get(b, 1.0) * self.partial_values(b, w)
        return out

    def eliminate(self, weights=None) -> float:
        return self.evaluate(weights)

    def cancellation(self) -> float:
        return 1.0

    def evaluate_cached(self, weights, options=None):
        from probsum.plans.model import Trace

        return self.evaluate(weights), Trace()

    def size(self):
        out = {"terms": 0, "factors": 0, "log10_monomials": float(sum(np.log10(s) for s in self.sizes.values()))}
        out["variables"] = sum(self.sizes.values()) + sum(self.sizes[a] * self.sizes[b] for a, b in self.edges)
        out["statistics"] = sum(self.sizes.values()) + sum(f.size for f in self.families)
        return out


def build_model(values, families: list[Family] = (), n=None, max_terms: int = 20_000) -> Model:
    """Terms while they are few; beyond `max_terms`, messages along the forest of pairs where they form one."""
    try:
        return Model(values, families, n, max_terms=max_terms)
    except TooManyTerms:
        try:
            return ForestModel(values, families, n)
        except ValueError:
            return Model(values, families, n)
