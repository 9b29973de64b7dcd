"""A sketch that estimates how many pairs a set of at most k attributes leaves together: a uniform sample of pairs.

With s = K k ln m / (alpha eps^2) pairs, a set that leaves at least an alpha share of the pairs is estimated within a factor 1 +- eps, and one that leaves
at most alpha/100 is called small. Fewer than alpha s / 10 hits mean "small".
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sepkey.functions import bounds
from sepkey.operators import exact, sampling
from sepkey.sources import stores

Sets = list[tuple[str, list[str]]]
#: Sets answered in one aggregate; longer lists take several.
_WIDE = 60


class PairSketch:
    """``flags``: slot and for each attribute whether the pair agrees on it; ``about``: n, m, k, alpha, eps, big_k, s."""

    def __init__(self, flags: DataFrame, attrs: list[str], about: dict):
        self.flags, self.attrs, self.about = flags, attrs, about

    @classmethod
    def build(cls, df: DataFrame, k: int, alpha: float, eps: float, seed: int, identity: list[Column], attrs: list[str] | None = None, big_k: float = 1.0, keep: bool = True, rows: DataFrame | None = None, n: int | None = None) -> PairSketch:
        attrs = attrs or df.columns
        s = bounds.sketch_pairs(len(attrs), k, alpha, eps, big_k)
        rows = rows if rows is not None else sampling.ordinals(df.select("*"), identity)
        n = n if n is not None else rows.count()
        flags = sampling.equal_flags(sampling.pairs(df, s, seed, identity, rows=rows, n=n), attrs)
        if keep:
            flags = stores.durable(flags, "sketch")
        return cls(flags, attrs, {"n": n, "m": len(attrs), "k": k, "alpha": float(alpha), "eps": float(eps), "big_k": float(big_k), "s": s})

    @classmethod
    def of_pairs(cls, pairs: DataFrame, s: int, n: int, k: int, alpha: float, eps: float, attrs: list[str], big_k: float = 1.0) -> PairSketch:
        """The sketch over given uniform pairs (slot, l, r), such as those kept from a stream."""
        flags = stores.durable(sampling.equal_flags(pairs, attrs), "sketch")
        return cls(flags, attrs, {"n": n, "m": len(attrs), "k": k, "alpha": float(alpha), "eps": float(eps), "big_k": float(big_k), "s": s})

    def first(self, k: int, alpha: float, eps: float) -> PairSketch:
        """The sketch of the same seed for smaller demands: pairs are drawn by slot, so that it is this one's first pairs."""
        s = bounds.sketch_pairs(self.about["m"], k, alpha, eps, self.about["big_k"])
        if s > self.about["s"]:
            raise ValueError(f"{s} pairs are asked for, {self.about['s']} are kept")
        return PairSketch(self.flags.where(F.col("slot") < s), self.attrs, self.about | {"k": k, "alpha": float(alpha), "eps": float(eps), "s": s})

    def _check(self, sets: Sets) -> None:
        for name, attrs in sets:
            if len(set(attrs)) > self.about["k"]:
                raise ValueError(f"{name}: the sketch answers sets of at most {self.about['k']} attributes")

    def hits(self, sets: Sets) -> DataFrame:
        """set_name, hits: sampled pairs that agree on the whole set. One pass for all sets."""
        self._check(sets)
        out = None
        for lo in range(0, len(sets), _WIDE):
            some = sets[lo : lo + _WIDE]
            cols = []
            for i, (_, attrs) in enumerate(some):
                cond = F.lit(True)
                for a in attrs:
                    cond = cond & F.col(a)
                cols.append(F.count_if(cond).alias(f"h{i}"))
            one = self.flags.agg(*cols).select(F.explode(F.array(*[F.struct(F.lit(n).alias("set_name"), F.col(f"h{i}").alias("hits")) for i, (n, _) in enumerate(some)])).alias("x")).select("x.*")
            out = one if out is None else out.unionByName(one)
        return out

    def estimate_many(self, sets: Sets) -> DataFrame:
        """set_name, hits, status ('small' or 'estimate'), gamma_hat (null where small)."""
        small = F.col("hits") < self.about["alpha"] * self.about["s"] / 10
        scaled = F.col("hits") / F.lit(self.about["s"]) * F.lit(float(bounds.pairs_of(self.about["n"])))
        return self.hits(sets).select("set_name", "hits", F.when(small, "small").otherwise("estimate").alias("status"), F.when(~small, F.round(scaled)).cast("long").alias("gamma_hat"))

    def estimate(self, attrs: list[str]) -> dict:
        return self.estimate_many([(",".join(attrs), attrs)]).first().asDict()

    def bits(self, per_value: float = 64.0) -> float:
        """Bits of the stored pairs at ``per_value`` a value. The flags alone take one bit a value."""
        return 2 * self.about["s"] * self.about["m"] * per_value

    def stored_bits(self) -> int:
        """Bits that the flags of the kept pairs take as they are: one for each pair and attribute."""
        return self.flags.count() * self.about["m"]

    def save(self, path: str) -> None:
        stores.save(self.flags, path, self.about)

    @classmethod
    def load(cls, spark, path: str) -> PairSketch:
        flags, about = stores.load(spark, path)
        return cls(flags, [c for c in flags.columns if c != "slot"], about)


def zones(estimates: DataFrame, truth: DataFrame, alpha: float, eps: float) -> DataFrame:
    """set_name, zone and whether the answer keeps the guarantee. truth: set_name, n, gamma. Zones: 'low' (at most alpha/100 of the pairs: must be
    small), 'high' (at least alpha: must be estimated within eps), 'between' (small, or within eps)."""
    total = exact.pairs(F.col("n")).cast("double")
    gamma = F.col("gamma").cast("double")
    zone = F.when(gamma <= alpha / 100 * total, "low").when(gamma >= alpha * total, "high").otherwise("between")
    close = F.abs(F.col("gamma_hat") / gamma - 1) <= eps
    small = F.col("status") == "small"
    ok = F.when(F.col("zone") == "low", small).when(F.col("zone") == "high", ~small & close).otherwise(small | close)
    both = estimates.join(truth.select("set_name", "n", "gamma"), "set_name").withColumn("zone", zone)
    return both.withColumn("holds", F.coalesce(ok, F.lit(False))).withColumn("relative_error", F.when(~small, F.col("gamma_hat") / gamma - 1))
