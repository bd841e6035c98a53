"""Answers from a solved model. Weights are per attribute: 0/1 for a predicate, values for a sum."""

from __future__ import annotations

import time
from itertools import combinations, product

import numpy as np

from probsum.plans.model import Model

Weights = dict[str, np.ndarray]


def mask(model: Model, attr: str, codes) -> np.ndarray:
    out = np.zeros(model.sizes[attr])
    out[list(codes)] = 1.0
    return out


def estimate(model: Model, weights: Weights, method: str = "mask") -> float:
    """Expected count of the tuples selected by the weights.

    mask: one evaluation with the excluded variables at 0. points: the sum over matching points, one evaluation
    each. derivative: the mixed partial of a point query by coefficient extraction. extend: over the expanded polynomial's
    monomials. The last three are the baselines the first replaces.
    """
    if method == "mask":
        return model.n * model.evaluate(weights) / model.evaluate()
    if method == "eliminate":
        return model.n * model.eliminate(weights) / model.eliminate()
    if method == "points":
        on = {a: np.flatnonzero(w) for a, w in weights.items()}
        total = 0.0
        for point in product(*on.values()):
            scale = float(np.prod([weights[a][x] for a, x in zip(on, point)]))
            total += scale * estimate(model, {a: mask(model, a, [x]) for a, x in zip(on, point)})
        return total
    if method == "derivative":
        # P is linear in each family: the coefficient of the chosen variables' product, times the variables
        on = {a: np.flatnonzero(w) for a, w in weights.items()}
        if any(len(x) != 1 for x in on.values()):
            raise ValueError("the derivative form takes point queries")
        first, *others = on.items()
        part = model.partial_values(first[0], {a: mask(model, a, x) for a, x in others})
        code = first[1][0]
        return model.n * model.alpha[first[0]][code] * part[code] * float(np.prod([weights[a][x[0]] for a, x in on.items()])) / model.evaluate()
    if method == "extend":
        w = [weights.get(a, np.ones(model.sizes[a])) for a in model.attrs]
        tuples, weight = expand(model)
        hit = np.prod([w[i][tuples[:, i]] for i in range(len(w))], axis=0)
        return float(model.n * (hit * weight).sum() / weight.sum())
    raise ValueError(method)


def expand(model: Model, most: int = 5_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Every possible tuple and its monomial: the expanded polynomial, for small domains."""
    sizes = [model.sizes[a] for a in model.attrs]
    if np.prod([float(s) for s in sizes]) > most:
        raise ValueError("too many possible tuples to expand")
    tuples = np.stack([g.ravel() for g in np.meshgrid(*[np.arange(s) for s in sizes], indexing="ij")], axis=1)
    at = {a: i for i, a in enumerate(model.attrs)}
    weight = np.ones(len(tuples))
    for a in model.attrs:
        weight *= model.alpha[a][tuples[:, at[a]]]
    for f, fam in enumerate(model.families):
        for r in range(fam.size):
            inside = np.logical_and.reduce([fam.masks[a][r][tuples[:, at[a]]] for a in fam.attrs])
            weight[inside] *= model.delta[f][r]
    return tuples, weight


def worlds_partition(model: Model) -> float:
    """Sum over all ordered instances of n tuples of the product of their monomials: P to the n; toy sizes only."""
    _, weight = expand(model, 64)
    n = int(model.n)
    if len(weight) ** n > 2_000_000:
        raise ValueError("too many worlds")
    return float(sum(np.prod(weight[list(w)]) for w in product(range(len(weight)), repeat=n)))


def expected_statistic(model: Model, family, j: int) -> float:
    """n * variable * partial / P of one statistic; family is an attribute's name or a family number."""
    p = model.evaluate()
    if isinstance(family, str):
        return float(model.n * model.alpha[family][j] * model.partial_values(family)[j] / p)
    return float(model.n * model.delta[family][j] * model.partial_rects(family)[0][j] / p)


def estimate_any(model: Model, clauses: list[Weights]) -> float:
    """Count of a disjunction of 0/1 conjunctions, by inclusion and exclusion."""
    total = 0.0
    for k in range(1, len(clauses) + 1):
        for some in combinations(clauses, k):
            both: Weights = {}
            for w in some:
                for a, v in w.items():
                    both[a] = both[a] * v if a in both else v
            total += (-1) ** (k + 1) * estimate(model, both)
    return total


def estimate_sum(model: Model, attr: str, values: np.ndarray, weights: Weights | None = None) -> float:
    """Expected sum of a function of one attribute (its bucket midpoints, say) over the selected tuples."""
    w = dict(weights or {})
    w[attr] = w.get(attr, 1.0) * np.asarray(values, dtype=np.float64)
    return estimate(model, w)


def estimate_avg(model: Model, attr: str, values: np.ndarray, weights: Weights | None = None) -> float:
    count = estimate(model, weights or {})
    return estimate_sum(model, attr, values, weights) / count if count > 0 else float("nan")


def estimate_groups(model: Model, by: list[str], weights: Weights | None = None) -> np.ndarray:
    """Expected counts of all groups of up to any number of attributes, as an array with one axis per attribute.

    One pass yields all groups of two attributes, as P is linear in each family; further attributes are fixed
    value by value.
    """
    w = dict(weights or {})
    scale = model.n / model.evaluate()
    if len(by) == 1:
        return scale * model.alpha[by[0]] * w.get(by[0], 1.0) * model.partial_values(by[0], w)
    if len(by) > 2:
        lead = min(by, key=lambda a: model.sizes[a])
        rest = [a for a in by if a != lead]
        parts = []
        for x in range(model.sizes[lead]):
            parts.append(estimate_groups(model, rest, {**w, lead: mask(model, lead, [x]) * w.get(lead, 1.0)}))
        out = np.stack(parts)
        return np.moveaxis(out, range(len(by)), [by.index(a) for a in (lead, *rest)])
    a, b = by
    if hasattr(model, "groups2"):
        return scale * model.groups2(a, b, w)
    inner = {k: v for k, v in w.items() if k not in by}
    base = model._free(inner, (a, b))
    va, vb = np.ones(model.sizes[a]), np.ones(model.sizes[b])
    both = None
    for c in model.components:
        if a in c.attrs and b in c.attrs:
            rest = model._component(c, inner, (a, b))
            fa, fb = c.factors[a], c.factors[b]
            cell = np.bincount(c.index[a] * len(fb) + c.index[b], rest, minlength=len(fa) * len(fb))
            both = fa.T @ cell.reshape(len(fa), len(fb)) @ fb
        elif a in c.attrs or b in c.attrs:
            x = a if a in c.attrs else b
            got = np.bincount(c.index[x], model._component(c, inner, (x,)), minlength=len(c.factors[x])) @ c.factors[x]
            va, vb = (va * got, vb) if x == a else (va, vb * got)
        else:
            base *= model._component(c, inner).sum()
    grid = both if both is not None else np.outer(va, vb)
    wa, wb = model.alpha[a] * w.get(a, 1.0), model.alpha[b] * w.get(b, 1.0)
    return scale * base * wa[:, None] * wb[None, :] * grid


def estimate_points(model: Model, by: list[str], weights: Weights | None = None, budget_s: float | None = None):
    """The same groups by one query each, and whether the time budget ended it early (the rest is NaN)."""
    out = np.full([model.sizes[a] for a in by], np.nan)
    end = time.monotonic() + budget_s if budget_s is not None else None
    for point in np.ndindex(*out.shape):
        if end is not None and time.monotonic() > end:
            return out, True
        w = dict(weights or {})
        for a, x in zip(by, point):
            w[a] = w.get(a, 1.0) * mask(model, a, [x])
        out[point] = estimate(model, w)
    return out, False


def rounded(est):
    """Nearest integer; below one half is none."""
    return np.floor(np.asarray(est) + 0.5).astype(np.int64)


def exists(est):
    return rounded(est) > 0


def tuple_probability(model: Model, point: dict[str, int]) -> float:
    """Probability that an instance holds the point at least once: 1 - (1 - p)^n."""
    p = estimate(model, {a: mask(model, a, [x]) for a, x in point.items()}) / model.n
    return float(-np.expm1(model.n * np.log1p(-min(p, 1 - 1e-16))))


def variance(model: Model, weights: Weights) -> float:
    """n p (1 - p): slots are independent and alike."""
    p = estimate(model, weights) / model.n
    return model.n * p * (1 - p)


def log_probability(model: Model, counts: dict[tuple[int, ...], int]) -> float:
    """Log-probability of an ordered instance given as counts of code tuples (in the order of model.attrs)."""
    at = {a: i for i, a in enumerate(model.attrs)}
    total, n = 0.0, 0
    with np.errstate(divide="ignore"):
        for t, k in counts.items():
            n += k
            total += k * sum(np.log(model.alpha[a][t[at[a]]]) for a in model.attrs)
            for f, fam in enumerate(model.families):
                for r in range(fam.size):
                    if all(fam.masks[a][r][t[at[a]]] for a in fam.attrs):
                        total += k * np.log(model.delta[f][r])
    return float(total - n * np.log(model.evaluate()))


def entropy(model: Model) -> float:
    """Entropy of the distribution over instances: n ln P less the targets' share of the logarithms."""
    return -model.dual()
