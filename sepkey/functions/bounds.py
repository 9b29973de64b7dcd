"""Sample sizes, miss probabilities and lower bounds, as numbers.

m: attributes; n: rows; r: sampled tuples; s: sampled pairs; eps: share of pairs that may stay together; delta: failure probability.
Natural logarithms throughout. Functions named ``log_...`` return logarithms, so that probabilities like e^-300 stay usable.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

import numpy as np


def pairs_of(n):
    return n * (n - 1) // 2


# -- sample sizes

#: The proof's constants: draws are 2 sqrt(8) K m / sqrt(eps), with K large enough for its tail bound.
PROOF_K = 100
PROOF_PAIRS = 10


def tuple_sample_size(m: int, eps: float, mode: str = "practical", c: float = 1.0, delta: float = 0.01, scope: str = "all", family: int | None = None, largest: int | None = None, n: int | None = None) -> int:
    """practical: c m / sqrt(eps) to the nearest integer. proof: the constants of the analysis. calibrated: the least r for which the
    worst two-valued profile is missed with probability at most delta over the number of sets: all 2^m (``scope='all'``), one
    (``'each'``), a list of ``family`` sets, or those of at most ``largest`` attributes."""
    if mode == "practical":
        return round(c * m / math.sqrt(eps))
    if mode == "proof":
        return math.ceil(2 * math.sqrt(8) * PROOF_K * m / math.sqrt(eps))
    if mode != "calibrated":
        raise ValueError(mode)
    target = math.log(delta) - log_sets(m, scope, family, largest)
    lo, hi = 2, 4
    while worst_profile(hi, eps)["log_miss"] > target:
        lo, hi = hi, hi * 2
    while lo + 1 < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if worst_profile(mid, eps)["log_miss"] <= target else (mid, hi)
    return hi if n is None else min(hi, n)


def pair_sample_size(m: int, eps: float, mode: str = "practical", c: float = 1.0, delta: float = 0.01, scope: str = "all", family: int | None = None, largest: int | None = None) -> int:
    """practical: c m / eps to the nearest integer; proof: 10 m / eps; calibrated: (1 - eps)^s at most delta over the number of sets."""
    if mode == "practical":
        return round(c * m / eps)
    if mode == "proof":
        return math.ceil(PROOF_PAIRS * m / eps)
    return math.ceil((math.log(delta) - log_sets(m, scope, family, largest)) / math.log1p(-eps))


def log_sets(m: int, scope: str = "all", family: int | None = None, largest: int | None = None) -> float:
    """ln of the number of sets that must all be answered rightly."""
    if scope == "each":
        return 0.0
    if family is not None:
        return math.log(family)
    if largest is not None:
        return math.log(sum(math.comb(m, i) for i in range(1, largest + 1)))
    return m * math.log(2)


def least_rows(r: int, m: int) -> float:
    """Rows must exceed this for sampling without replacement to be within e^m of sampling with."""
    return r * (r - 1) / m + r - 1


def check_regime(n: int, m: int, r: int, eps: float) -> dict:
    """Whether the analysis covers these sizes. Outside it the filter still runs; with r >= n it is exact."""
    enough = n > least_rows(r, m)
    in_lemma = 4 <= r <= 1 + (1 - math.sqrt(eps) / 2) * n
    return {"enough_rows": enough, "lemma_range": in_lemma, "exact": r >= n, "guaranteed": r >= n or (enough and in_lemma)}


def sketch_pairs(m: int, k: int, alpha: float, eps: float, big_k: float = 1.0) -> int:
    return math.ceil(big_k * k * math.log(m) / (alpha * eps**2))


# -- non-collision


def log_elementary(sizes: Iterable[tuple[float, int]], r: int) -> float:
    """ln of the r-th elementary symmetric polynomial of a histogram (size, how many), by a product of binomial series in log space: the factor of
    ``k`` equal sizes a is (1 + a x)^k."""
    poly = np.full(r + 1, -np.inf)
    poly[0] = 0.0
    for size, count in sizes:
        if size <= 0 or count <= 0:
            continue
        top = min(int(count), r)
        j = np.arange(top + 1)
        factor = _log_choose(count, j) + j * math.log(size)
        out = np.full(r + 1, -np.inf)
        for i in range(top + 1):
            np.logaddexp(out[i:], poly[: r + 1 - i] + factor[i], out=out[i:])
        poly = out
    return float(poly[r])


def _log_choose(n, k):
    n, k = np.asarray(n, float), np.asarray(k, float)
    return np.vectorize(math.lgamma)(n + 1) - np.vectorize(math.lgamma)(k + 1) - np.vectorize(math.lgamma)(n - k + 1)


def log_noncollision(sizes: list[tuple[float, int]], r: int, replacement: bool = True) -> float:
    """ln of the probability that r tuples fall into r different groups."""
    n = sum(a * k for a, k in sizes)
    e = log_elementary(sizes, r)
    if replacement:
        return math.lgamma(r + 1) - r * math.log(n) + e
    return math.lgamma(r + 1) - (math.lgamma(n + 1) - math.lgamma(n - r + 1)) + e


def noncollision(sizes, r: int, replacement: bool = True) -> float:
    return math.exp(log_noncollision(sizes, r, replacement))


def log_replacement_ratio(n: int, r: int) -> float:
    """ln of n^r / (n (n-1) ... (n-r+1)): the factor from drawing with to drawing without replacement."""
    return r * math.log(n) - (math.lgamma(n + 1) - math.lgamma(n - r + 1))


def log_two_valued(r: int, share_a: float, ka: int, share_b: float, kb: float = math.inf) -> float:
    """ln non-collision, with replacement, of ka groups that hold share_a together and kb groups (inf: infinitely small ones) that hold share_b:
    sum over i of C(r,i) P(i draws in A, all different) P(r-i draws in B, all different)."""
    i = np.arange(0, min(ka, r) + 1)
    out = _log_choose(r, i)
    with np.errstate(divide="ignore"):
        out = out + np.where(i > 0, i * math.log(max(share_a, 1e-300)), 0.0) + _log_fall(ka, i) - i * math.log(ka)
        rest = r - i
        out = out + np.where(rest > 0, rest * math.log(max(share_b, 1e-300)), 0.0)
        if not math.isinf(kb):
            ok = rest <= kb
            out = np.where(ok, out + _log_fall(kb, np.minimum(rest, kb)) - rest * math.log(kb), -np.inf)
    top = out.max()
    return float(top + math.log(np.exp(out - top).sum())) if np.isfinite(top) else -math.inf


def _log_fall(n, k):
    """ln of n (n - 1) ... (n - k + 1), for whole k."""
    k = np.asarray(k).astype(np.int64)
    with np.errstate(divide="ignore", invalid="ignore"):
        steps = np.log(np.maximum(float(n) - np.arange(int(k.max(initial=0))), 0.0))
    return np.concatenate([[0.0], np.cumsum(steps)])[k]


#: A wider family than the planner scans: more groups of the one size, beside finitely many of the other.
WIDE_GROUPS = (*range(1, 17), 24, 32, 48, 64, 128, 256, 512, 1024)
WIDE_REST = (math.inf, *(2.0**k for k in range(1, 31)))


def worst_profile(r: int, eps: float, relaxed: bool = False, groups: Iterable[int] = (1, 2, 3, 4, 6, 8, 12, 16, 32, 64), rest: Iterable[float] = (math.inf,)) -> dict:
    """The two-valued profile that is bad (its pairs are an eps share; a quarter of it in the relaxed form of the analysis) and most likely missed,
    among ka groups of one size beside kb smaller ones."""
    share = eps / 4 if relaxed else eps
    best = {"log_miss": -math.inf, "ka": 0, "kb": 0.0}
    for ka in groups:
        for kb in rest:
            if math.isinf(kb):
                x = math.sqrt(share * ka)  # ka groups of mass x/ka: pairs share x^2/ka
                if x > 1:
                    continue
            else:
                # x^2/ka + (1-x)^2/kb = share, the larger root
                a, b, c = 1 / ka + 1 / kb, -2 / kb, 1 / kb - share
                d = b * b - 4 * a * c
                if d < 0:
                    continue
                x = (-b + math.sqrt(d)) / (2 * a)
                if not 0 <= x <= 1:
                    continue
            miss = log_two_valued(r, x, ka, 1 - x, kb)
            if miss > best["log_miss"]:
                best = {"log_miss": miss, "ka": ka, "kb": float(kb)}
    return best


def compare_profiles(r: int, eps: float) -> dict:
    """Equal groups against one heavy group with single rows: with r beyond 1/eps the first cannot be missed, the second can."""
    q = math.floor(1 / eps)
    equal = log_two_valued(r, 1.0, q, 0.0) if r <= q else -math.inf
    return {"equal": equal, "heavy": log_two_valued(r, math.sqrt(eps), 1, 1 - math.sqrt(eps))}


def log_pair_miss(eps: float, s: int) -> float:
    """ln of the chance that s pairs all miss a bad set."""
    return s * math.log1p(-eps)


def group_argument(ka: int, eps: float, m: int, big_k: float = PROOF_K) -> dict:
    """The two-group step: the heavier group's share, the draws made, and the draws that fall into it on average."""
    share = min(1.0, math.sqrt(eps * ka / 8))
    draws = 2 * math.sqrt(8) * big_k * m / math.sqrt(eps)
    return {"share": share, "draws": draws, "expected": draws * share, "needed": big_k * m * math.sqrt(ka)}


def final_union(m: int) -> dict:
    """ln of each side of the two closing inequalities: per bad set, and over all sets."""
    per = m + np.logaddexp(-20.0 * m * m, -20.0 * m)
    return {"per_set": float(per), "per_set_bound": -10.0 * m, "all_sets": m * math.log(2) - 10.0 * m, "all_sets_bound": -1.0 * m}


# -- lower bounds


def log_grid_no_collision(q: int, r: int) -> float:
    return float(np.sum(np.log1p(-np.arange(r) / q))) if r <= q else -math.inf


def grid_detection(q: int, m: int, r: int, replacement: bool = True) -> dict:
    """On the grid with q values: the chance that all m single attributes are detected, and the chain of bounds up to 1/e. Without replacement, draws
    are those with replacement given that no row comes twice, so that every bound grows by one over the chance of that: at most twofold
    while it is at least a half."""
    none = math.exp(log_grid_no_collision(q, r))
    apart = 1.0 if replacement else math.exp(log_grid_no_collision(q**m, r)) if r <= q**m else 0.0
    grow = lambda x: min(1.0, x / apart) if apart else 1.0
    chain = {"exact": (1 - none) ** m, "bound": (1 - math.exp(-(r**2) / q)) ** m, "ceiling": (1 - 1 / m) ** m if m > 1 else 0.0, "one_over_e": math.exp(-1)}
    return {k: grow(v) for k, v in chain.items()} | {"rows_apart": apart, "in_regime": m <= 2.0**q}


def constant_failure_tuples(m: int, eps: float) -> float:
    return math.sqrt(math.log(m) / eps)


def planted_miss(n: int, c: int, r: int, replacement: bool = False) -> float:
    """The chance that at most one of r tuples lies in a cluster of c among n rows."""
    if replacement:
        p = c / n
        return (1 - p) ** r + r * p * (1 - p) ** (r - 1)
    lc = lambda a, b: -math.inf if b > a or b < 0 else math.lgamma(a + 1) - math.lgamma(b + 1) - math.lgamma(a - b + 1)
    return sum(math.exp(lc(c, i) + lc(n - c, r - i) - lc(n, r)) for i in (0, 1) if lc(n - c, r - i) > -math.inf)


def planted_size(n: int, eps: float) -> int:
    """The least cluster, up to one row, whose pairs exceed an eps share."""
    return math.ceil(math.sqrt(eps) * n) + 1


def sketch_bits_lower(m: int, k: int, eps: float) -> float:
    return m * k * math.log(1 / eps)


def sketch_samples_lower(k: int, eps: float) -> float:
    return k * math.log(1 / eps)


def sketch_bits_upper(m: int, k: int, alpha: float, eps: float, bits_per_value: float = 64.0, big_k: float = 1.0) -> float:
    return 2 * sketch_pairs(m, k, alpha, eps, big_k) * m * bits_per_value


def block_gamma(t: int, k: int, u: int) -> int:
    """Unseparated pairs of a guess with u of k rows right, in the block table with n = k t; doubled terms keep it integral."""
    twice = (2 * t * t - 2 * t + 5) * k * k - (2 * t - 1) * k + 2 * u * u - 6 * k * u
    return twice // 2


def block_gamma_by_groups(t: int, k: int, u: int) -> int:
    n = k * t
    return pairs_of(n + k - u) + pairs_of(n - 2 * k + u)


def decoder_threshold(t: float, k: int, eps: float) -> float:
    return (1 + eps) * ((t * t - t + 0.5) * k * k - (t - 0.5) * k)


def decoder_eps(t: float) -> float:
    """Errors below this keep a guess with at most 0.9 k right rows apart from the right one."""
    return 11 / (200 * t * t - 200 * t + 111)


def decoder_t(eps: float, big_k: float = 1.0) -> float:
    return 1 / (big_k * math.sqrt(eps))


def decoder_gap(t: float) -> tuple[float, float]:
    """Leading coefficients at u = 0.9 k and u = k."""
    return t * t - t + 0.61, t * t - t + 0.5


def counting_bound(k: int, m: int, t: int) -> dict:
    """ln of the inputs near one reconstruction, of all inputs, and the failure that follows."""
    size = m * k * t
    i = np.arange(0, size // (10 * t) + 1)
    terms = _log_choose(size, i)
    top = terms.max()
    near = float(top + math.log(np.exp(terms - top).sum()))
    total = m * float(_log_choose(t * k, k))
    return {"log_near": near, "log_total": total, "failure": 1 - math.exp(min(0.0, -0.8 * k * m * math.log(t)))}


def sketch_tail(s: int, p: float, eps: float) -> float:
    """Bound on the chance that a binomial count with mean s p is off by more than a factor 1 +- eps."""
    return min(1.0, 2 * math.exp(-(eps**2) * s * p / 3))


def small_tail(k: int, m: int, eps: float, big_k: float = 1.0) -> float:
    """Bound on the chance that a set with at most alpha/100 of the pairs is not called small."""
    return min(1.0, 2 * math.exp(-4.5 * big_k * k * math.log(m)))
