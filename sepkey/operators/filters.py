"""Filters for separation keys: accept or reject any set of attributes from one sample.

Every key is accepted with certainty; a set that leaves more than an eps share of the pairs together is rejected with high probability,
for all sets at once; anything between may get either answer.

``TupleFilter`` keeps about m / sqrt(eps) tuples and accepts a set if no two of them agree on it. ``PairFilter``, the older baseline, keeps about
m / eps pairs and accepts if each pair differs somewhere on the set. ``ExactFilter`` looks at all rows.

Samples are small by construction (their size depends on m and eps alone), so ``accepts`` and ``query_many`` work on integer codes of the sample, held
by the driver; ``query_df`` answers inside Spark, and the sample can be stored and loaded.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sepkey.functions import bounds
from sepkey.operators import exact, sampling
from sepkey.sources import stores

Sets = list[tuple[str, list[str]]]


def codes_of(table: pa.Table) -> dict[str, np.ndarray]:
    """Dense integer codes of each column of a collected sample, equal where Spark groups values together: nulls are one value, all NaNs are one,
    and zeros of either sign. Values never pass through floats of another type, so that wide integers stay apart."""
    return {a: _column_codes(table.column(i).combine_chunks()) for i, a in enumerate(table.column_names)}


def _column_codes(values: pa.Array) -> np.ndarray:
    kind = values.type
    if isinstance(values, pa.ChunkedArray):
        values = pa.concat_arrays(values.chunks) if values.num_chunks else pa.array([], kind)
    if pa.types.is_floating(kind):
        bits = np.nan_to_num(values.cast(pa.float64()).fill_null(0.0).to_numpy(zero_copy_only=False), nan=np.nan, posinf=np.inf, neginf=-np.inf) + 0.0
        whole = np.where(np.isnan(bits), np.int64(-1), bits.view(np.int64))  # all ones: one of the NaNs
        values = pa.array(whole, mask=np.asarray(values.is_null()))
    elif pa.types.is_nested(kind):
        known: dict = {}
        return np.fromiter((known.setdefault(_plain(v, kind), len(known)) for v in values.to_pylist(maps_as_pydicts=None)), np.int64, len(values))
    return pc.dictionary_encode(values, null_encoding="encode").indices.to_numpy(zero_copy_only=False).astype(np.int64)


def _plain(v, kind: pa.DataType):
    """A hashable stand-in of a nested value, equal where Spark's grouping is."""
    if v is None:
        return None
    if pa.types.is_floating(kind):
        return "NaN" if v != v else v + 0.0
    if pa.types.is_map(kind):
        return tuple(sorted(((_plain(k, kind.key_type), _plain(x, kind.item_type)) for k, x in v), key=repr))
    if pa.types.is_struct(kind):
        return tuple(_plain(v[f.name], f.type) for f in kind)
    if pa.types.is_nested(kind):
        return tuple(_plain(x, kind.value_type) for x in v)
    return v


def refine(group: np.ndarray, code: np.ndarray) -> np.ndarray:
    """Dense ids of (group, code)."""
    return np.unique(group * (int(code.max(initial=0)) + 1) + code, return_inverse=True)[1]


class _Monotone:
    """Answers for many sets with the lattice's short cuts: supersets of accepted sets are accepted, subsets of rejected ones rejected."""

    def query_many(self, sets: Sets) -> dict[str, bool]:
        accepted: list[frozenset] = []
        rejected: list[frozenset] = []
        out = {}
        for name, attrs in sorted(sets, key=lambda x: len(x[1])):
            s = frozenset(attrs)
            if any(a <= s for a in accepted):
                out[name] = True
            elif any(s <= r for r in rejected):
                out[name] = False
            else:
                out[name] = self.accepts(attrs)
                (accepted if out[name] else rejected).append(s)
        return out


class TupleFilter(_Monotone):
    def __init__(self, sample: DataFrame, attrs: list[str], about: dict):
        self.sample, self.attrs, self.about = sample, attrs, about
        self._code: dict[str, np.ndarray] | None = None

    @classmethod
    def build(cls, df: DataFrame, eps: float, seed: int, identity: list[Column], attrs: list[str] | None = None, mode: str = "practical", r: int | None = None, replacement: bool = False, keep: bool = True, rank: str = "md5", derive=None, **planner) -> TupleFilter:
        """``keep`` sees to it that queries read a written sample and do not draw it anew. With replacement, a row drawn twice counts once: two draws of one row
        are no evidence against a set. ``derive`` makes the attributes from sampled rows, where they are costly to make for all."""
        derive = derive or (lambda rows: rows)
        attrs = attrs or df.columns
        r = r if r is not None else bounds.tuple_sample_size(len(attrs), eps, mode, **planner)
        if replacement:
            drawn = sampling.tuples_wr(df, r, seed, identity)
            sample = derive(drawn.dropDuplicates(["ordinal"])).select(*attrs)
            n = None
        else:
            n = df.count() if keep else None
            if n is not None and r < n and r * len(attrs) <= LOCAL_CELLS and _plain_types(df, attrs):
                # one scan straight to the driver, which holds the sample's codes in any case
                drawn = derive(sampling.tuples(df, r, seed, identity, rank, n, write=False)).select(*attrs)
                rows = drawn.toArrow()
                if rows.num_rows == r:
                    kept = cls(df.sparkSession.createDataFrame(rows, drawn.schema), attrs, _about(eps, attrs, r, n, seed))
                    kept._code = codes_of(rows)
                    return kept
            sample = sampling.tuples(df, r, seed, identity, rank, n)
            sample = derive(sample).select(*attrs)
        if keep and (n is None or r >= n):  # below a threshold the rows are written already
            sample = stores.durable(sample.coalesce(1), "sample")
        return cls(sample, attrs, _about(eps, attrs, r, n, seed))

    def codes(self) -> dict[str, np.ndarray]:
        if self._code is None:
            self._code = codes_of(self.sample.select(*[F.col(f"`{a}`") for a in self.attrs]).toArrow())
        return self._code

    def accepts(self, attrs: list[str]) -> bool:
        """Refines the sample's groups attribute by attribute, the most selective first, on the rows that are not yet alone."""
        code = self.codes()
        n = len(next(iter(code.values()), ()))
        if n < 2:
            return True
        if not attrs:
            return False
        order = sorted(attrs, key=lambda a: -int(code[a].max(initial=0)))
        rows, group = np.arange(n), np.zeros(n, np.int64)
        for a in order:
            group = refine(group, code[a][rows])
            size = np.bincount(group)
            left = size[group] > 1
            if not left.any():
                return True
            rows, group = rows[left], group[left]
        return False

    def query_df(self, sets: Sets, strategy: str = "hash") -> DataFrame:
        """set_name, accept. hash: one pass with 128 bits of hash for each set and row (a key is rejected only if two of the sampled rows collide in
        all of them); grouping_sets and lattice compare the values; sort: neighbours in sorted order are compared, set by set."""
        if strategy == "sort":
            out = None
            for name, attrs in sets:
                one = self._sorted(name, attrs)
                out = one if out is None else out.unionByName(one)
            return out
        many = exact.unseparated_many(self.sample, sets, "fingerprint" if strategy == "hash" else strategy)
        return many.select("set_name", (F.col("gamma") == 0).alias("accept"))

    def _sorted(self, name: str, attrs: list[str]) -> DataFrame:
        row = F.struct(*[F.struct(F.col(a).isNull().alias(f"{a}_null"), F.col(a)) for a in attrs])
        ordered = self.sample.select(row.alias("v")).withColumn("before", F.lag("v").over(Window.orderBy("v")))  # the sample's rows
        return ordered.agg(F.coalesce(~F.bool_or(F.col("before").isNotNull() & F.col("v").eqNullSafe(F.col("before"))), F.lit(True)).alias("accept")).select(F.lit(name).alias("set_name"), "accept")

    def witness(self, attrs: list[str], row_id: str) -> DataFrame:
        """The groups of sampled rows that agree on ``attrs``: size, and their two smallest ids."""
        return self.sample.groupBy(*attrs).agg(F.count("*").alias("size"), F.array_sort(F.collect_list(row_id)).alias("ids")).where("size > 1").select(*attrs, "size", F.element_at("ids", 1).alias("first_id"), F.element_at("ids", 2).alias("second_id"))

    def plugin_gamma(self, sets: Sets, n: int) -> DataFrame:
        """Gamma scaled up from the sample's own pairs; for comparison with the pair sketch."""
        many = exact.unseparated_many(self.sample, sets)
        return many.select("set_name", (F.col("gamma").cast("double") / exact.pairs(F.col("n")).cast("double") * float(bounds.pairs_of(n))).alias("gamma_plugin"))

    def save(self, path: str) -> None:
        stores.save(self.sample, path, self.about)

    @classmethod
    def load(cls, spark, path: str) -> TupleFilter:
        rows, about = stores.load(spark, path)
        return cls(rows, rows.columns, about)


#: Most values of a sample that is collected as it is drawn; larger ones are written first.
LOCAL_CELLS = 500_000


def _plain_types(df: DataFrame, attrs: list[str]) -> bool:
    kinds = {f.name: f.dataType for f in df.schema}
    return all(a in kinds and isinstance(kinds[a], (T.NumericType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)) for a in attrs)


def _about(eps: float, attrs: list[str], r: int, n: int | None, seed: int) -> dict:
    about = {"kind": "tuples", "eps": float(eps), "m": len(attrs), "r": r, "n": n if n is not None else -1, "seed": seed}
    return about if n is None else about | {"guaranteed": bool(bounds.check_regime(n, len(attrs), r, eps)["guaranteed"])}


class PairFilter(_Monotone):
    """``flags``: slot and for each attribute whether the pair agrees on it."""

    def __init__(self, flags: DataFrame, attrs: list[str], about: dict):
        self.flags, self.attrs, self.about = flags, attrs, about
        self._masks: list[int] | None = None
        self._packed: np.ndarray | None = None

    @classmethod
    def build(cls, df: DataFrame, eps: float, seed: int, identity: list[Column], attrs: list[str] | None = None, mode: str = "practical", s: int | None = None, pair_mode: str = "independent", keep: bool = True, rows: DataFrame | None = None, n: int | None = None, **planner) -> PairFilter:
        attrs = attrs or df.columns
        s = s if s is not None else bounds.pair_sample_size(len(attrs), eps, mode, **planner)
        flags = sampling.equal_flags(sampling.pairs(df, s, seed, identity, pair_mode, rows, n), attrs)
        if keep:
            flags = stores.durable(flags, "pairs")
        return cls(flags, attrs, {"kind": "pairs", "eps": float(eps), "m": len(attrs), "s": s, "seed": seed})

    @classmethod
    def build_graded(cls, df: DataFrame, eps: float, seed: int, identity: list[Column], codes: list[str], moduli: tuple, attrs: list[str], s: int | None = None, rows: DataFrame | None = None, n: int | None = None) -> PairFilter:
        """For very many attributes that are remainders of few integer codes: pairs carry the codes, and each pair becomes one string of bits (attribute differs),
        made in batches of Arrow."""
        s = s if s is not None else bounds.pair_sample_size(len(attrs), eps)
        whole = df.select("*", F.array(*codes).alias("__v")) if rows is None else rows
        met = sampling.pairs(whole.select("__v"), s, seed, identity, rows=whole, n=n) if rows is not None else sampling.pairs(whole, s, seed, identity)
        flags = stores.map_arrow(met.select("slot", F.col("l.__v").alias("l"), F.col("r.__v").alias("r")), _graded_bits(moduli), "slot long, differs binary")
        return cls(stores.durable(flags, "pairs"), attrs, {"kind": "pairs", "eps": float(eps), "m": len(attrs), "s": s, "seed": seed})

    def matrix(self) -> np.ndarray:
        """Pairs by attributes: agrees."""
        if "differs" in self.flags.columns:
            return ~np.unpackbits(self._bits(), axis=1, bitorder="little")[:, : len(self.attrs)].astype(bool)
        return self.flags.select(*self.attrs).toPandas().to_numpy(bool)

    def _bits(self) -> np.ndarray:
        blobs = self.flags.select("differs").toPandas()["differs"]
        return np.frombuffer(b"".join(map(bytes, blobs)), np.uint8).reshape(len(blobs), -1)

    def packed(self) -> np.ndarray:
        """Distinct rows of bits (attribute differs), eight attributes a byte."""
        if self._packed is None:
            bits = self._bits() if "differs" in self.flags.columns else np.packbits(~self.matrix(), axis=1, bitorder="little")
            rows = np.ascontiguousarray(bits).view(f"V{bits.shape[1]}").ravel() if len(bits) else bits
            self._packed = bits[np.unique(rows, return_index=True)[1]] if len(bits) else bits
        return self._packed

    def minimal_masks(self) -> list[int]:
        """Distinct masks of the attributes on which a pair differs, without those that hold another: a set that meets all minimal ones meets all."""
        if self._masks is None:
            self._masks = minimal_masks([int.from_bytes(row.tobytes(), "little") for row in self.packed()])
        return self._masks

    def accepts(self, attrs: list[str]) -> bool:
        at = {a: i for i, a in enumerate(self.attrs)}
        left = np.arange(len(self.packed()))
        for a in attrs:  # pairs that are told apart leave
            if not len(left):
                break
            i = at[a]
            left = left[(self.packed()[left, i >> 3] >> (i & 7)) & 1 == 0]
        return not len(left)

    def query_df(self, sets: Sets) -> DataFrame:
        """set_name, accept: one aggregate with a condition for each set, ``_WIDE`` sets at a time."""
        out = None
        for lo in range(0, len(sets), _WIDE):
            some = sets[lo : lo + _WIDE]
            missed = [F.coalesce(F.bool_or(_all(attrs)), F.lit(False)).alias(f"m{i}") for i, (_, attrs) in enumerate(some)]
            one = self.flags.agg(*missed).select(F.explode(F.array(*[F.struct(F.lit(n).alias("set_name"), (~F.col(f"m{i}")).alias("accept")) for i, (n, _) in enumerate(some)])).alias("x")).select("x.*")
            out = one if out is None else out.unionByName(one)
        return out

    def save(self, path: str) -> None:
        stores.save(self.flags, path, self.about)

    @classmethod
    def load(cls, spark, path: str) -> PairFilter:
        flags, about = stores.load(spark, path)
        return cls(flags, [c for c in flags.columns if c != "slot"], about)


_WIDE = 40


def _graded_bits(moduli: tuple):
    def run(batches):
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            left, right = (batch.column(i).flatten().to_numpy(zero_copy_only=False).reshape(n, -1) for i in (1, 2))
            differs = np.stack([(left != right) if b is None else (left % b != right % b) for b in moduli], axis=2).reshape(n, -1)
            bits = np.packbits(differs, axis=1, bitorder="little")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.tobytes() for r in bits], pa.binary())], ["slot", "differs"])

    return run


def _all(attrs: list[str]) -> Column:
    out = F.lit(True)
    for a in attrs:
        out = out & F.col(a)
    return out


def mask_of(attrs: list[str], order: list[str]) -> int:
    at = {a: i for i, a in enumerate(order)}
    return sum(1 << at[a] for a in set(attrs))


def minimal_masks(masks: list[int]) -> list[int]:
    out: list[int] = []
    for m in sorted(set(masks), key=lambda x: (x.bit_count(), x)):
        if not any(k & m == k for k in out):
            out.append(m)
    return out


class ExactFilter:
    """Accepts keys alone and rejects everything else: the filter whose sample is the table."""

    def __init__(self, df: DataFrame, eps: float):
        self.df, self.eps = df, eps

    def accepts(self, attrs: list[str]) -> bool:
        return exact.is_key(self.df, attrs)

    def query_df(self, sets: Sets, strategy: str = "fingerprint") -> DataFrame:
        many = exact.unseparated_many(self.df, sets, strategy)
        return many.select("set_name", (F.col("gamma") == 0).alias("accept"), exact.verdict_of(F.col("gamma"), F.col("n"), self.eps).alias("verdict"))
