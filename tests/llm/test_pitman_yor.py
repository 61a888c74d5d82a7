"""The seating against its exact distribution, against seating customer by customer, and the model's sum over all words."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pytest

from charprobe.llm import common, hpy_lm, pitman_yor


def test_stirling_numbers_by_plain_recursion():
    table, row = pitman_yor.stirling_table(0.5, 8), [0.0, 1.0]
    for c in range(1, 8):
        for t in range(1, c + 1):
            assert abs(table[c, t] - math.log(row[t])) < 1e-9
        row = [0.0] + [(row[t - 1]) + (c - 0.5 * t) * (row[t] if t < len(row) else 0.0) for t in range(1, c + 2)]


@pytest.mark.parametrize("d", [0.3, 0.7])
def test_large_counts_follow_the_recursion(d):
    table = pitman_yor.stirling_table(d, 1500)
    t = np.array([3, 10, 60, 200])
    assert np.abs(pitman_yor.log_stirling(d, np.full(4, 1500), t, table[:1025, :1025]) - table[1500, t]).max() < 0.03


def test_tables_are_drawn_from_their_distribution(monkeypatch):
    rng, d = np.random.default_rng(0), 0.6
    for exact in (1024, 40):  # with 40, the larger counts take the proposal of Metropolis and Hastings
        monkeypatch.setattr(pitman_yor, "EXACT", exact)
        table = pitman_yor.stirling_table(d, exact)
        for c, y in ((2, 0.4), (6, 0.2), (60, 3.0)):
            t = np.ones(20_000, np.int64)
            for _ in range(8):
                t = pitman_yor.draw_tables(np.full(20_000, c), np.full(20_000, math.log(y)), d, table, rng, t)
            w = np.exp(pitman_yor.stirling_table(d, c)[c, 1:] + np.arange(1, c + 1) * math.log(y) - 200 * (c > 50))
            want = (w / w.sum() * np.arange(1, c + 1)).sum()
            assert abs(t.mean() - want) < 0.06 * max(1.0, want**0.5), (exact, c)


def customer_by_customer(counts, d, a, d0, a0, sweeps, rng):
    """Mean P(w | u) when every customer is taken out and seated anew in turn, with all tables kept: the plain sampler."""
    n_u, n_w = counts.shape
    seats = [[[] for _ in range(n_w)] for _ in range(n_u)]  # sizes of the tables of (u, w)
    root = [[] for _ in range(n_w)]

    def base(w):
        return (sum(root[w]) - d0 * len(root[w]) + (a0 + d0 * sum(map(len, root))) / n_w) / (a0 + sum(map(sum, root)))

    def seat(tables, discount, new):
        p = np.array([s - discount for s in tables] + [new])
        k = int(rng.choice(len(p), p=p / p.sum()))
        if k == len(tables):
            tables.append(1)
            return True
        tables[k] += 1
        return False

    def leave(tables):
        k = int(rng.choice(len(tables), p=np.array(tables) / sum(tables)))
        tables[k] -= 1
        if not tables[k]:
            del tables[k]
            return True
        return False

    def enter(u, w):
        if seat(seats[u][w], d, (a + d * sum(map(len, seats[u]))) * base(w)):
            seat(root[w], d0, (a0 + d0 * sum(map(len, root))) / n_w)

    customers = [(u, w) for u in range(n_u) for w in range(n_w) for _ in range(counts[u, w])]
    for u, w in customers:
        enter(u, w)
    out = np.zeros((n_u, n_w))
    for k in range(sweeps):
        for u, w in customers:
            if leave(seats[u][w]):
                leave(root[w])
            enter(u, w)
        if k >= sweeps // 5:
            for u, w in itertools.product(range(n_u), range(n_w)):
                t = sum(map(len, seats[u]))
                out[u, w] += (counts[u, w] - d * len(seats[u][w]) + (a + d * t) * base(w)) / (a + counts[u].sum())
    return out / (sweeps - sweeps // 5)


def test_blocked_sampler_equals_seating_customer_by_customer():
    """Both levels together: the mean predictive probabilities of the two samplers agree."""
    rng = np.random.default_rng(4)
    counts = np.array([[5, 1, 0, 0], [2, 2, 1, 0], [0, 0, 3, 1], [1, 0, 0, 0]])
    d, a, d0, a0 = 0.5, 1.0, 0.4, 1.0
    want = customer_by_customer(counts, d, a, d0, a0, 1500, rng)
    u, w = np.nonzero(counts)
    c, t, table, table0 = counts[u, w], np.ones(len(u), np.int64), pitman_yor.stirling_table(d), pitman_yor.stirling_table(d0)
    t0, got, rounds = np.ones(4, np.int64), np.zeros((4, 4)), 6000
    for k in range(rounds):
        own = np.bincount(w, weights=t, minlength=4).astype(np.int64)
        t0 = pitman_yor.sweep(np.zeros(4, np.int64), own, np.minimum(t0, own), np.array([float(np.minimum(t0, own).sum())]), np.full(4, math.log(0.25)), d0, a0, table0, rng)
        weight, rest = rng.gamma(own - d0 * t0), rng.gamma(a0 + d0 * t0.sum())
        parent = (weight + rest / 4) / (weight.sum() + rest)
        t = pitman_yor.sweep(u, c, t, np.bincount(u, weights=t, minlength=4), np.log(parent)[w], d, a, table, rng)
        if k >= rounds // 5:
            own = np.bincount(w, weights=t, minlength=4)
            t0_mean = np.minimum(t0, own)
            mean = (own - d0 * t0_mean + (a0 + d0 * t0_mean.sum()) / 4) / (a0 + own.sum())
            tables = np.bincount(u, weights=t, minlength=4)
            p = ((a + d * tables) / (a + counts.sum(1)))[:, None] * mean[None, :]
            p[u, w] += (c - d * t) / (a + counts.sum(1))[u]
            got += p
    assert np.abs(got / (rounds - rounds // 5) - want).max() < 0.02


def test_probabilities_sum_to_one():
    """Known dishes, and the base's mass of all words of all lengths: each context's sum is 1."""
    sizes = np.arange(1, 400)
    total = sum(math.comb(int(n), int(k)) * 26.0**k * float(hpy_lm.OTHERS) ** (n - k) * float(np.exp(hpy_lm.letter_logs(np.array([k]), np.array([n]))[0])) for n in range(1, 40) for k in range(n + 1))
    assert abs(total - (1 - hpy_lm.ENDS) * (1 - (1 - hpy_lm.LAST) ** 39)) < 1e-9 and len(sizes)
    rng = np.random.default_rng(0)
    words = np.sort(rng.integers(10, 1 << 62, 12).astype(np.uint64))
    key = np.unique(rng.integers(0, 60, 40))
    counts = rng.integers(1, 9, len(key)).astype(np.uint32)
    short, contexts = common.packed(words[:5])
    words_short, names = common.packed(words)
    small, large = common.in_bytes(counts)
    base = np.full(12, -8.0, np.float32)
    state = {"short": short, "contexts": contexts, "runs": np.bincount(key // 12, minlength=5).astype(np.uint32).tobytes(), "words_short": words_short, "words": names, "places": hpy_lm.as_places(key % 12, 12), "counts": small, "large": large, "extra": base.tobytes()}
    own0 = np.bincount(key % 12, minlength=12)
    d0, a0 = 0.4, 2.0
    p = {"d": 0.6, "a": 1.5, "weight": float((own0 - d0 * (own0 > 0)).sum()), "rest": a0 + d0 * float((own0 > 0).sum())}
    room = hpy_lm.Room(state, p)
    room.hear({"runs": (own0 - d0 * (own0 > 0)).astype(float).tobytes(), "counts": own0.astype(np.int64).tobytes()})
    own, rest = room.sweeps(6, 4, rng)
    unknown = (1 - np.exp(base.astype(float)).sum()) * p["rest"] / (p["weight"] + p["rest"])  # of the parent, in words that no text has
    for u in range(5):
        assert abs(own[room.u == u].sum() + rest[u] * (room.parent().sum() + unknown) - 1) < 1e-9


def test_parameters_are_drawn_near_the_truth():
    rng, d, a = np.random.default_rng(1), 0.7, 10.0
    rows = []
    for _ in range(60):  # dishes of a base without atoms: every table has a dish of its own, so c counts one table each
        tables: list[int] = []
        for n in range(400):
            p = np.array([s - d for s in tables] + [a + d * len(tables)])
            k = int(rng.choice(len(p), p=p / p.sum()))
            if k == len(tables):
                tables.append(0)
            tables[k] += 1
        rows += pitman_yor.histogram(np.array(tables), np.ones(len(tables)), np.array([400]), np.array([len(tables)]))
    drawn = [pitman_yor.draw_parameters(rows, rng) for _ in range(5)]
    assert abs(np.mean([x for x, _ in drawn]) - d) < 0.1 and all(3 <= y <= 30 for _, y in drawn)


def test_pairs_are_listed_in_little_memory():
    """A task's pairs are dealt within 110 bytes each besides the given columns, which are let go (two workers share an executor)."""
    import tracemalloc

    n = 400_000
    rng = np.random.default_rng(5)
    dish = rng.integers(3, (1 << 64) - 1, n // 4, dtype=np.uint64)[rng.integers(0, n // 4, n)]
    opens = np.arange(n) % 100 == 0
    tracemalloc.start()
    try:
        held = [(opens.copy(), dish.copy(), np.zeros(n, np.float32), np.ones(n, np.uint8))]
        blobs = 0
        for b in hpy_lm.pair_blobs(held, 8, False):
            blobs += 1
            _, words, _, _, counts = hpy_lm.read_pairs(b)
            assert np.isin(words, dish).all() and len(counts)
        most = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert blobs == 8 and not held and most < 110 * n
