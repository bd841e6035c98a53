"""The factorised maximum-entropy polynomial: terms, evaluation, partial derivatives, fitting.

A model has attributes with N_i values, a variable per value, and families of disjoint rectangles with a
variable per rectangle. P is the sum over groups of compatible rectangles (one per family at most, jointly
intersecting) of the product of the attributes' sums restricted to the intersection, times (delta - 1) for
every rectangle of the group. Families that share no attribute multiply, so P is a product of components.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Family:
    """Disjoint rectangles over some attributes: masks[attr] is (rectangles x values), bool."""

    attrs: tuple[str, ...]
    masks: dict[str, np.ndarray]
    targets: np.ndarray

    @property
    def size(self) -> int:
        return len(self.targets)


@dataclass
class Component:
    """Terms of the families that are connected by attributes."""

    attrs: list[str]
    families: list[int]
    factors: dict[str, np.ndarray]  # attr: distinct masks (factors x values)
    index: dict[str, np.ndarray]  # attr: factor of each term
    rects: np.ndarray  # terms x families, -1 for none

    @property
    def terms(self) -> int:
        return len(self.rects)


@dataclass
class Trace:
    """What an evaluation could skip."""

    terms: int = 0
    reused: int = 0
    zero: int = 0

    @property
    def hit_rate(self) -> float:
        return (self.reused + self.zero) / self.terms if self.terms else 0.0


@dataclass(frozen=True)
class EvalOptions:
    cache: bool = True
    masks: bool = True
    zeros: bool = True


class TooManyTerms(ValueError):
    pass


def grow_groups(families: list[Family], which: list[int], sizes: dict[str, int], most: int) -> tuple[list[str], list[dict], np.ndarray]:
    """Compatible groups, family by family: each is kept as it is, or extended by a rectangle that still intersects.

    Returns attributes, and the running masks and rectangle numbers of the groups; every group appears once.
    """
    attrs = sorted({a for f in which for a in families[f].attrs})
    masks = {a: np.ones((1, sizes[a]), dtype=bool) for a in attrs}
    rects = np.full((1, len(which)), -1, dtype=np.int64)
    for at, f in enumerate(which):
        fam = families[f]
        ok = np.ones((len(rects), fam.size), dtype=bool)
        for a in fam.attrs:
            ok &= masks[a].astype(np.float32) @ fam.masks[a].T.astype(np.float32) > 0.5
        g, r = np.nonzero(ok)
        if len(rects) + len(g) > most:
            raise TooManyTerms(f"over {most} terms at family {f}")
        new_rects = rects[g].copy()
        new_rects[:, at] = r
        for a in attrs:
            ext = masks[a][g] & fam.masks[a][r] if a in fam.attrs else masks[a][g]
            masks[a] = np.concatenate([masks[a], ext])
        rects = np.concatenate([rects, new_rects])
    return attrs, masks, rects


class Model:
    """Polynomial and parameters; sizes: {attr: N}, values: {attr: counts of its values}."""

    def __init__(self, values: dict[str, np.ndarray], families: list[Family] = (), n: float | None = None,
                 split_components: bool = True, max_terms: int = 2_000_000):
        self.attrs = list(values)
        self.values = {a: np.asarray(v, dtype=np.float64) for a, v in values.items()}
        self.sizes = {a: len(v) for a, v in self.values.items()}
        self.n = float(n if n is not None else next(iter(self.values.values())).sum())
        self.families = list(families)
        self.alpha = {a: np.where(v > 0, v / max(self.n, 1e-300), 0.0) for a, v in self.values.items()}
        self.delta = [np.where(f.targets > 0, 1.0, 0.0) for f in self.families]
        self.history: list[tuple[int, str, float]] = []
        self._check()
        parts = self._connected() if split_components else ([list(range(len(self.families)))] if self.families else [])
        self.components = [self._build(p, max_terms) for p in parts]
        used = {a for c in self.components for a in c.attrs}
        self.free = [a for a in self.attrs if a not in used]

    def _check(self) -> None:
        for a, v in self.values.items():
            if abs(v.sum() - self.n) > 1e-6 * max(1.0, self.n) or (v < 0).any():
                raise ValueError(f"the counts of {a} do not sum to n")
        for f in self.families:
            both = np.ones((f.size, f.size), dtype=np.int64)
            for a in f.attrs:
                both = both * (f.masks[a].astype(np.float32) @ f.masks[a].T.astype(np.float32) > 0.5)
            if (np.triu(both, 1) > 0).any():
                raise ValueError(f"rectangles on {f.attrs} overlap")
            if (f.targets < 0).any() or f.targets.sum() > self.n * (1 + 1e-9):
                raise ValueError(f"targets on {f.attrs} exceed n")

    def _connected(self) -> list[list[int]]:
        groups: list[tuple[set[str], list[int]]] = []
        for i, f in enumerate(self.families):
            hit = [g for g in groups if g[0] & set(f.attrs)]
            merged = (set(f.attrs).union(*[g[0] for g in hit]), sorted([i, *[j for g in hit for j in g[1]]]))
            groups = [g for g in groups if g not in hit] + [merged]
        return [g[1] for g in groups]

    def _build(self, which: list[int], max_terms: int) -> Component:
        attrs, masks, rects = grow_groups(self.families, which, self.sizes, max_terms)
        factors, index = {}, {}
        for a in attrs:
            packed = np.packbits(masks[a], axis=1)
            _, first, inverse = np.unique(packed, axis=0, return_index=True, return_inverse=True)
            factors[a], index[a] = masks[a][first], inverse.reshape(-1)
        return Component(attrs, which, factors, index, rects)

    # -- evaluation ---------------------------------------------------------

    def _coefficients(self, c: Component, without: int | None = None) -> np.ndarray:
        out = np.ones(c.terms)
        for at, f in enumerate(c.families):
            if f != without and self.families[f].size:
                r = c.rects[:, at]
                out *= np.where(r >= 0, self.delta[f][r] - 1, 1.0)
        return out

    def _sums(self, c: Component, weights: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        return {a: c.factors[a] @ (self.alpha[a] * weights[a] if a in weights else self.alpha[a]) for a in c.attrs}

    def _component(self, c: Component, weights, skip: tuple[str, ...] = (), without: int | None = None) -> np.ndarray:
        """Value of every term, the sums of `skip` and the rectangles of `without` left out."""
        term = self._coefficients(c, without)
        for a, s in self._sums(c, weights).items():
            if a not in skip:
                term = term * s[c.index[a]]
        return term

    def _free(self, weights, skip: tuple[str, ...] = ()) -> float:
        return float(
            np.prod([(self.alpha[a] * weights[a] if a in weights else self.alpha[a]).sum() for a in self.free if a not in skip])
        )

    def evaluate(self, weights: dict[str, np.ndarray] | None = None) -> float:
        """P with every variable of value x of attribute a multiplied by weights[a][x]."""
        weights = weights or {}
        out = self._free(weights)
        for c in self.components:
            out *= self._component(c, weights).sum()
        return float(out)

    def refresh(self) -> None:
        """Store what an unrestricted evaluation needs: factor sums, term products, component values."""
        self._cache = [
            (self._sums(c, {}), coef := self._coefficients(c), self._component(c, {})) for c in self.components
        ]
        self._cached_p = [float(t.sum()) for *_, t in self._cache]

    def evaluate_cached(self, weights: dict[str, np.ndarray], options: EvalOptions = EvalOptions()) -> tuple[float, Trace]:
        """evaluate() that reuses stored sums of unrestricted attributes and drops terms with a zero factor early."""
        if not hasattr(self, "_cache"):
            self.refresh()
        trace = Trace()
        out = self._free(weights)
        for c, (sums, coef, _), whole in zip(self.components, self._cache, self._cached_p, strict=True):
            trace.terms += c.terms
            touched = [a for a in c.attrs if a in weights]
            if options.cache and options.masks and not touched:
                trace.reused += c.terms
                out *= whole
                continue
            live = np.arange(c.terms)
            part = {}
            for a in c.attrs:
                if a in weights or not options.cache:
                    part[a] = c.factors[a] @ (self.alpha[a] * weights.get(a, 1.0))
                else:
                    part[a] = sums[a]
                if options.zeros and a in weights:
                    live = live[part[a][c.index[a][live]] != 0]
            trace.zero += c.terms - len(live)
            term = (coef if options.cache else self._coefficients(c))[live]
            for a in c.attrs:
                term = term * part[a][c.index[a][live]]
            out *= term.sum()
        return float(out), trace

    def partial_values(self, attr: str, weights: dict[str, np.ndarray] | None = None) -> np.ndarray:
        """dP / d alpha of all values of an attribute (P is linear in them)."""
        weights = {k: v for k, v in (weights or {}).items() if k != attr}
        if attr in self.free:
            base = self._free(weights, (attr,))
            for c in self.components:
                base *= self._component(c, weights).sum()
            return np.full(self.sizes[attr], base)
        base, out = self._free(weights), None
        for c in self.components:
            if attr in c.attrs:
                rest = np.bincount(c.index[attr], self._component(c, weights, (attr,)), minlength=len(c.factors[attr]))
                out = rest @ c.factors[attr]
            else:
                base *= self._component(c, weights).sum()
        return out * base

    def partial_rects(self, f: int) -> tuple[np.ndarray, float]:
        """(Q, P0): dP / d delta of a family's rectangles, and P with all of them 0."""
        base = self._free({})
        q, p0 = None, 0.0
        for c in self.components:
            if f in c.families:
                r = c.rects[:, c.families.index(f)]
                rest = self._component(c, {}, without=f)
                q = np.bincount(r[r >= 0], rest[r >= 0], minlength=self.families[f].size)
                p0 = rest[r < 0].sum() - q.sum()
            else:
                base *= self._component(c, {}).sum()
        return q * base, max(p0 * base, 0.0)

    def cancellation(self) -> float:
        """|sum| / sum of absolute terms, the least over the components: near 0 the alternating sum has lost its digits."""
        out = 1.0
        for c in self.components:
            t = self._component(c, {})
            out = min(out, abs(t.sum()) / max(np.abs(t).sum(), 1e-300))
        return float(out)

    # -- size ---------------------------------------------------------------

    def size(self) -> dict[str, float]:
        """Terms, distinct factors, variable occurrences of the factorised form, and monomials of the expanded one."""
        occurrences = sum(self.sizes[a] for a in self.free)
        for c in self.components:
            for a in c.attrs:
                occurrences += int(c.factors[a].sum(axis=1)[c.index[a]].sum())
            occurrences += int((c.rects >= 0).sum())
        return {
            "terms": sum(c.terms for c in self.components),
            "factors": sum(len(m) for c in self.components for m in c.factors.values()),
            "variables": occurrences,
            "log10_monomials": float(sum(np.log10(s) for s in self.sizes.values())),
            "statistics": sum(self.sizes.values()) + sum(f.size for f in self.families),
        }

    # -- fitting ------------------------------------------------------------

    def step_values(self, attr: str) -> None:
        """Solve all values of an attribute at once: alpha = target / partial; targets of 0 stay pinned at 0."""
        part, s = self.partial_values(attr), self.values[attr]
        with np.errstate(divide="ignore", invalid="ignore"):
            new = np.where((s > 0) & (part > 0), s / part, 0.0)
        total = new.sum()
        self.alpha[attr] = new / total if total > 0 else new

    def step_rects(self, f: int) -> None:
        """Solve a family of disjoint rectangles at once; a family that holds all rows has no outside."""
        q, p0 = self.partial_rects(f)
        s = self.families[f].targets
        rest = self.n - s.sum()
        with np.errstate(divide="ignore", invalid="ignore"):
            if rest > 1e-9 * max(self.n, 1.0) and p0 > 0:
                new = s * p0 / (rest * q)
            else:  # all rows lie inside: the outside keeps a weight of one part in 10^10
                new = s / q * max(1.0, 1e10 * p0 / max(self.n, 1e-300))
        self.delta[f] = np.where((s > 0) & (q > 0) & np.isfinite(new), new, 0.0)

    def step_coordinate(self, kind: str, key, j: int) -> None:
        """The exact step of one variable: s (P - alpha P_j) / ((n - s) P_j)."""
        if kind == "value":
            part = self.partial_values(key)
            a, s = self.alpha[key], self.values[key][j]
            p, pj = float(a @ part), part[j]
        else:
            q, p0 = self.partial_rects(key)
            a, s = self.delta[key], self.families[key].targets[j]
            p, pj = p0 + float(a @ q), q[j]
        if s <= 0 or s >= self.n or pj <= 0:
            return  # pinned, or left to the block step
        a[j] = s * (p - a[j] * pj) / ((self.n - s) * pj)

    def residuals(self) -> dict:
        """Largest |target - expectation| of every attribute and family."""
        out: dict = {}
        p = self.evaluate()
        for a in self.attrs:
            out[a] = float(np.abs(self.values[a] - self.n * self.alpha[a] * self.partial_values(a) / p).max())
        for f, fam in enumerate(self.families):
            if fam.size:
                q, _ = self.partial_rects(f)
                out[f] = float(np.abs(fam.targets - self.n * self.delta[f] * q / p).max())
        return out

    def dual(self) -> float:
        """Objective that fitting raises: sum of target * ln(variable) - n ln P, over variables that are not pinned."""
        total = -self.n * np.log(self.evaluate())
        for a in self.attrs:
            on = self.values[a] > 0
            total += float(self.values[a][on] @ np.log(self.alpha[a][on]))
        for f, fam in enumerate(self.families):
            on = fam.targets > 0
            total += float(fam.targets[on] @ np.log(self.delta[f][on]))
        return float(total)

    def _gradient_step(self, rate: float) -> None:
        """One step of gradient ascent on the logarithms of all variables; the gradient is target - expectation."""
        p = self.evaluate()
        up_a = {a: self.values[a] - self.n * self.alpha[a] * self.partial_values(a) / p for a in self.attrs}
        up_d = [fam.targets - self.n * self.delta[f] * self.partial_rects(f)[0] / p for f, fam in enumerate(self.families)]
        for a in self.attrs:
            self.alpha[a] = self.alpha[a] * np.exp(np.clip(rate * up_a[a] / self.n, -5, 5))
            self.alpha[a] /= self.alpha[a].sum()
        for f in range(len(self.families)):
            self.delta[f] = self.delta[f] * np.exp(np.clip(rate * up_d[f] / self.n, -5, 5))

    def solve(self, method: str = "block", max_sweeps: int = 30, tol: float = 1e-6, rate: float = 1.0, budget_s: float | None = None) -> "Model":
        """Sweep until the largest residual is under `tol` or `max_sweeps` are done; history keeps (sweep, family, residual).

        block: all variables of a family at once; coordinate: one variable at a time; gradient: ascent on the dual.
        The residual is measured on frozen parameters at the end of a sweep.
        """
        import time

        end = time.monotonic() + budget_s if budget_s else None
        for sweep in range(1, max_sweeps + 1):
            if method == "block":
                for a in self.attrs:
                    self.step_values(a)
                for f, fam in enumerate(self.families):
                    if fam.size:
                        self.step_rects(f)
            elif method == "coordinate":
                for a in self.attrs:
                    for j in range(self.sizes[a]):
                        self.step_coordinate("value", a, j)
                for f, fam in enumerate(self.families):
                    for j in range(fam.size):
                        self.step_coordinate("rect", f, j)
            elif method == "gradient":
                self._gradient_step(rate)
            else:
                raise ValueError(method)
            res = self.residuals()
            self.history += [(sweep, str(k), v) for k, v in res.items()]
            if max(res.values(), default=0.0) < tol or end and time.monotonic() > end:
                break
        self.__dict__.pop("_cache", None)
        return self

    # -- elimination --------------------------------------------------------

    def eliminate(self, weights: dict[str, np.ndarray] | None = None) -> float:
        """P by summing attributes out along the graph of pairs: no alternating terms. The pairs must form a forest."""
        weights = weights or {}
        nodes = {a: self.alpha[a] * weights.get(a, 1.0) for a in self.attrs}
        edges: dict[tuple[str, str], np.ndarray] = {}
        for f, fam in enumerate(self.families):
            if len(fam.attrs) != 2:
                raise ValueError("elimination takes rectangles over pairs")
            a, b = fam.attrs
            table = np.ones((self.sizes[a], self.sizes[b]))
            for r in range(fam.size):
                table[np.ix_(fam.masks[a][r], fam.masks[b][r])] = self.delta[f][r]
            edges[a, b] = edges[a, b] * table if (a, b) in edges else table
        edges = dict(edges)
        log = 0.0
        live = set(self.attrs)
        while live:
            leaf = next((a for a in sorted(live) if sum(a in e for e in edges) <= 1), None)
            if leaf is None:
                raise ValueError("the pairs form a cycle")
            e = next((e for e in edges if leaf in e), None)
            if e is None:
                total = nodes[leaf].sum()
                if total <= 0:
                    return 0.0
                log += np.log(total)
            else:
                t = edges.pop(e)
                other = e[1] if e[0] == leaf else e[0]
                message = nodes[leaf] @ t if e[0] == leaf else t @ nodes[leaf]
                nodes[other] = nodes[other] * message
            live.discard(leaf)
        return float(np.exp(log))
