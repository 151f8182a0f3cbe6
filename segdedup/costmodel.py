"""The closed forms: banding, residual collisions, fan-out and its optimum."""

from __future__ import annotations

import math

from segdedup import policies


def lsh_probability(j: float, bands: int, rows: int) -> float:
    return 1 - (1 - j**rows) ** bands


def residual_bound(u: float, bands: int = 16, bits: int = 64) -> float:
    return bands * u / 2.0**bits


def bloom_bits(n0: int, fp: float) -> tuple[int, int]:
    """Bits and hash functions for n0 keys at a false-positive rate."""
    bits = math.ceil(-n0 * math.log(fp) / math.log(2) ** 2)
    return bits, max(1, round(bits / n0 * math.log(2)))


def bloom_fpr(n: int, bits: int, k: int) -> float:
    return (1 - math.exp(-k * n / bits)) ** k


def lambert_w0(x: float) -> float:
    if x < -1 / math.e - 1e-12:
        raise ValueError("no real branch")
    w = math.log1p(x) if x > -0.25 else -1 + math.sqrt(max(0.0, 2 * (math.e * x + 1)))
    for _ in range(60):
        e = math.exp(w)
        f = w * e - x
        if w == -1 or abs(f) < 1e-15:
            break
        step = f / (e * (w + 1) - (w + 2) * f / (2 * w + 2))
        w -= step
        if abs(step) < 1e-15 * max(1, abs(w)):
            break
    return w


def rho(c_r: float, c_w: float, nu: float, m: float) -> float:
    return 2 * c_w / (c_r * math.log2(nu * m))


def fanout_closed_form(c_r: float, c_w: float, nu: float, m: float) -> float:
    return math.exp(1 + lambert_w0((rho(c_r, c_w, nu, m) - 1) / math.e))


def fanout_refined(c_r: float, c_w: float, nu: float, m: float, k: int) -> float:
    """Keeps the mean level's share of the search depth; minimised by golden section."""

    def cost(t: float) -> float:
        return ((t - 1) * (math.log(nu * m) + 0.5 * math.log(max(1.0, k / t))) + 2 * c_w * math.log(2) / c_r) / math.log(t)

    a, b, g = 1.01, 64.0, (math.sqrt(5) - 1) / 2
    for _ in range(100):
        c, d = b - g * (b - a), a + g * (b - a)
        a, b = (a, d) if cost(c) < cost(d) else (c, b)
    return (a + b) / 2


def validity(k: int, t: float, nu: float, m: float) -> float:
    return 0.5 * math.log(k / t) / math.log(nu * m)


def exact_cost(k: int, t: int, c_r: float, c_w: float, nu: float, m: float) -> float:
    """The discrete sum over releases: searches in each live segment, keys rewritten by merges."""
    result = policies.run(policies.Tiered(t), k)
    searched = sum(n * math.log2(max(2.0, nu * m)) for n in result["fanout"])
    return c_r * m * searched + c_w * m * result["written"]


def best_fanout(k: int, c_r: float, c_w: float, nu: float, m: float, upto: int = 16) -> int:
    return min(range(2, upto + 1), key=lambda t: exact_cost(k, t, c_r, c_w, nu, m))


def digit_sum(n: int, t: int) -> int:
    return 0 if n == 0 else n % t + digit_sum(n // t, t)


def live_segments(k: int, t: int) -> int:
    return digit_sum(k - 1, t) + 1


def total_fanout(k: int, t: int) -> int:
    return sum(digit_sum(i - 2, t) + 1 for i in range(2, k + 1))


def rewritten(k: int, t: int, coalesce: bool = False) -> int:
    """Keys that merges write over k releases, in units of a release."""
    n, out = k - 1, 0
    if coalesce:
        for i in range(t, n + 1, t):
            v = 0
            while i % t ** (v + 1) == 0:
                v += 1
            out += t**v
        return out
    level = 1
    while t**level <= n:
        out += t**level * (n // t**level)
        level += 1
    return out


def advise(n_docs: float, ram_bytes: float, releases: int, exact: bool, withdraw: bool) -> str:
    """Which system the properties call for."""
    if releases <= 1:
        return "snapshot_rebuild"
    if withdraw or (exact and n_docs * 6500 > ram_bytes):
        return "segmented_index"
    return "resident_table" if n_docs * 6500 <= ram_bytes else "bloom_bands"
