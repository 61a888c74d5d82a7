"""The seating of Pitman-Yor restaurants: generalised Stirling numbers, blocked Gibbs steps, draws of the parameters.

A restaurant with discount d and concentration a seats the customers of each dish at tables; a new table is a customer
of the parent. Let c customers of a dish sit at t tables. Summed over all seatings with these t, the joint probability is

    product of S_d(c, t) over the dishes  *  (a)(a + d)...(a + d(T - 1)) / ((a)(a + 1)...(a + C - 1))  *  product of parent(dish) ** t

where T and C are the restaurant's tables and customers. The rising product binds the dishes of a restaurant together;
with x drawn from Gamma(a / d + T) it falls apart into d**T x**T, so that given x and the parent's probabilities every
dish draws its t on its own, from all of 1..c with weights S_d(c, t) (d x parent(dish))**t. That is an exact Gibbs step for
all restaurants below one parent at once, and needs no order among them.
"""

from __future__ import annotations

import math

import numpy as np

#: Greatest count with Stirling numbers by recursion; beyond, they are taken at the saddle point, less its error at EXACT.
EXACT = 1024
lgamma = np.vectorize(math.lgamma, otypes=[np.float64])


def stirling_table(d: float, most: int = EXACT) -> np.ndarray:
    """log S_d(c, t) for 0 <= t <= c <= most, by the recursion over customers; -inf elsewhere."""
    out = np.full((most + 1, most + 1), -np.inf)
    out[0, 0] = 0.0
    t = np.arange(most + 1)
    with np.errstate(invalid="ignore", divide="ignore"):
        for c in range(most):
            out[c + 1, 1:] = np.logaddexp(out[c, :-1], np.log(np.maximum(c - d * t[1:], 0)) + out[c, 1:])
    return out


def _bisect(rising, n: int) -> np.ndarray:
    """Where a function of log q that rises on (-80, 0) passes zero."""
    low, high = np.full(n, -80.0), np.full(n, -1e-12)
    for _ in range(60):
        mid = (low + high) / 2
        above = rising(mid) > 0
        low, high = np.where(above, low, mid), np.where(above, mid, high)
    return (low + high) / 2


def at_saddle(d: float, c: np.ndarray, t: np.ndarray) -> np.ndarray:
    """log S_d(c, t) for 1 <= t < c by its generating function ((1 - (1 - z)**d) / d)**t / t! at the saddle point."""
    log_q = _bisect(lambda s: np.log(c / t) - (np.log(-np.expm1(s)) + (d - 1) * s + math.log(d) - np.log(-np.expm1(d * s))), len(c))
    q = np.exp(log_q)
    z, f = -np.expm1(log_q), -np.expm1(d * log_q) / d
    h = z * np.exp((d - 1) * log_q) / f
    spread = t * h * (1 + (1 - d) * z / q - h)
    return lgamma(c + 1) - lgamma(t + 1) + t * np.log(f) - c * np.log(z) - 0.5 * np.log(2 * math.pi * np.maximum(spread, 1e-12))


def log_stirling(d: float, c: np.ndarray, t: np.ndarray, table: np.ndarray) -> np.ndarray:
    """log S_d(c, t) for c beyond EXACT. The saddle point's error hardly changes along t / c**d, so that at EXACT is taken off."""
    c, t = np.asarray(c, float), np.asarray(t, float)
    most = len(table) - 1
    like = np.clip(t * (most / c) ** d, 1, most - 1)
    grid = np.unique(np.concatenate([np.floor(like), np.ceil(like)])) if len(c) else np.ones(1)
    error = table[most, grid.astype(int)] - at_saddle(d, np.full(len(grid), float(most)), grid)
    return at_saddle(d, c, t) + np.interp(like, grid, error)


def draw_tables(c: np.ndarray, log_y: np.ndarray, d: float, table: np.ndarray, rng: np.random.Generator, before: np.ndarray) -> np.ndarray:
    """Tables t of dishes with c customers, from weights S_d(c, t) y**t.

    Up to EXACT customers t is drawn from all its values; beyond, a normal draw about the peak is proposed and
    taken or left by Metropolis and Hastings, ``before`` being the state.
    """
    out = np.ones(len(c), np.int64)
    two = c == 2
    out[two] += rng.random(int(two.sum())) * (1 - d + np.exp(log_y[two])) >= 1 - d
    some = np.flatnonzero((c > 2) & (c <= EXACT))
    some = some[np.argsort(c[some], kind="stable")]
    values, first = np.unique(c[some], return_index=True)
    for k, lo, hi in zip(values.tolist(), first.tolist(), [*first[1:].tolist(), len(some)]):
        for a in range(lo, hi, max(1, 400_000 // k)):
            at = some[a : min(hi, a + max(1, 400_000 // k))]
            w = table[k, 1 : k + 1] + log_y[at, None] * np.arange(1, k + 1)
            w = np.cumsum(np.exp(w - w.max(axis=1, keepdims=True)), axis=1)
            out[at] = 1 + np.minimum((w < rng.random(len(at))[:, None] * w[:, -1:]).sum(axis=1), k - 1)
    big = np.flatnonzero(c > EXACT)
    if len(big):
        n, y = c[big].astype(float), log_y[big]
        s = _bisect(lambda s: np.log(n) - y - np.log(-np.expm1(s)) - (d - 1) * s, len(big))
        q, z, f = np.exp(s), -np.expm1(s), -np.expm1(d * s) / d
        peak = np.clip(np.exp(y) * f, 1, n - 1)
        h = z * np.exp((d - 1) * s) / f
        wide = 1.1 * np.sqrt(np.maximum(peak / (1 + h / np.maximum(1 + (1 - d) * z / q - h, 1e-9)), 0.5))
        old = np.clip(before[big], 1, c[big] - 1).astype(float)
        new = np.clip(np.round(peak + wide * rng.standard_normal(len(big))), 1, n - 1)
        gain = log_stirling(d, n, new, table) - log_stirling(d, n, old, table) + (new - old) * y + ((new - peak) ** 2 - (old - peak) ** 2) / (2 * wide**2)
        out[big] = np.where(np.log(rng.random(len(big))) < gain, new, old)
    return out


def sweep(restaurant: np.ndarray, c: np.ndarray, t: np.ndarray, tables: np.ndarray, log_parent: np.ndarray, d: float, a: float, table: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """One Gibbs step for all dishes of all restaurants (numbers ``restaurant``, with ``tables`` in all) below one parent."""
    x = rng.gamma(a / d + tables)
    return draw_tables(c, np.log(d * np.maximum(x, 1e-300))[restaurant] + log_parent, d, table, rng, t)


#: Values of the discount and of the concentration that are weighed against each other (fixed values).
DISCOUNTS = (0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.55, 0.6, 0.65, 0.7, 0.75, 0.8, 0.85, 0.9, 0.95)
CONCENTRATIONS = (0.1, 0.3, 1.0, 3.0, 10.0, 30.0, 100.0, 1000.0)


def coarse(values: np.ndarray) -> np.ndarray:
    """Values above EXACT by steps of 2 %, so that a histogram of them stays small."""
    v = np.asarray(values, float)
    return np.where(v <= EXACT, v, np.round(np.exp(np.round(np.log(np.maximum(v, 1)) / 0.02) * 0.02)))


def histogram(c: np.ndarray, t: np.ndarray, customers: np.ndarray, tables: np.ndarray) -> list[tuple[int, int, int, int]]:
    """What the parameters' draw needs: how many dishes have (c, t), kind 0, and how many restaurants (customers, tables), kind 1."""
    out = []
    for kind, a, b in ((0, c, t), (1, customers, tables)):
        pairs, n = np.unique(np.stack([coarse(a), coarse(b)]), axis=1, return_counts=True)
        out += [(kind, int(x), int(y), int(m)) for x, y, m in zip(*pairs, n)]
    return out


def draw_parameters(rows: list[tuple[int, int, int, int]], rng: np.random.Generator) -> tuple[float, float]:
    """Discount and concentration, drawn from their joint conditional on the grid above, uniform before."""
    dishes, rooms = (np.array([r[1:] for r in rows if r[0] == k], float).reshape(-1, 3) for k in (0, 1))
    dishes = dishes[dishes[:, 0] > 1]
    dishes[:, 1] = np.minimum(dishes[:, 1], dishes[:, 0])
    weight = np.zeros((len(DISCOUNTS), len(CONCENTRATIONS)))
    for i, d in enumerate(DISCOUNTS):
        small = dishes[:, 0] <= EXACT
        at = dishes[small].astype(int)
        table = stirling_table(d)
        fixed = float((table[at[:, 0], at[:, 1]] * at[:, 2]).sum())
        large = dishes[~small & (dishes[:, 1] < dishes[:, 0])]
        fixed += float((log_stirling(d, large[:, 0], large[:, 1], table) * large[:, 2]).sum()) if len(large) else 0.0
        for k, a in enumerate(CONCENTRATIONS):
            c, t, n = rooms.T
            weight[i, k] = fixed + float((n * (t * math.log(d) + lgamma(a / d + t) - lgamma(a + c))).sum()) - n.sum() * (math.lgamma(a / d) - math.lgamma(a))
    p = np.exp(weight - weight.max()).ravel()
    i, k = divmod(int(rng.choice(len(p), p=p / p.sum())), len(CONCENTRATIONS))
    return DISCOUNTS[i], CONCENTRATIONS[k]
