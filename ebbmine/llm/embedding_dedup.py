"""Near-duplicate embeddings by randomised-rotation binary codes.

Each vector is normalised and turned by seeded random rotations (as many as give `width` coordinates);
the signs are its code, packed to a bit a coordinate, and <code, turned vector> is its correction factor.
Codes and factors are computed once and stored beside the vectors. <code_x, turned y> / factor_x is an
unbiased estimate of the cosine of x and y with an error of about
sqrt((1 - factor^2) / factor^2 / (width - 1)) times a normal deviate.

1. Pairs meet in buckets: tables of a few code bits each, as many tables as a pair at the threshold
   needs to meet with probability `recall`. Only ids and packed codes are shuffled. The share of bits
   in which two codes differ estimates their angle; with its confidence bound it tells which documents
   of a bucket may have a partner there that no earlier table showed.
2. Vectors and factors are fetched for those documents only. In their buckets the estimate and its upper
   confidence bound decide which pairs are recomputed exactly in double precision; all others are settled.

Both bounds are `deviates` standard errors wide, so a pair at the threshold can be missed by the tables
(1 - recall) or by a bound (some 3 in 100,000 each at 4 deviates); what is linked is always exact.

Exact copies are one class with a weight. A bucket beyond `bucket_rows` is cut into blocks that meet
pairwise, so any bucket is compared whole, by tasks of bounded size; a pair that meets in several tables
counts in the first only. What leaves a task is linear in its rows: documents, counts of links, a spanning forest.

Vectors that are null, empty, zero or hold null or non-finite components, and rows of null id, link
with nothing. Vectors of different lengths link with nothing. Repeated ids are judged row by row.
Labels and extra columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType

from .common import only, tidy, written
from .graph import components

#: Coordinates of a code at least.
WIDTH = 256


class Coder:
    """Rotations, codes, correction factors and table keys for vectors of one length."""

    def __init__(self, dims: int, tables: int, bits: int, seed: int = 3):
        rng = np.random.default_rng([seed, dims])
        rounds = max(1, -(-max(WIDTH, 2 * bits) // dims))
        self.turns = [np.linalg.qr(rng.standard_normal((dims, dims)))[0] for _ in range(rounds)]
        self.dims, self.width = dims, dims * rounds
        self.picks = np.array([rng.permutation(self.width)[: min(bits, self.width)] for _ in range(tables)])
        self.powers = 1 << np.arange(self.picks.shape[1], dtype=np.int64)

    def turned(self, unit: np.ndarray) -> np.ndarray:
        """Unit vectors in all rotations, of length 1 again."""
        return np.concatenate([unit @ t.T for t in self.turns], 1) / math.sqrt(len(self.turns))

    def code(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Packed codes and correction factors."""
        turned = self.turned(unit)
        signs = turned >= 0
        return np.packbits(signs, axis=1, bitorder="little"), np.abs(turned).sum(1) / math.sqrt(self.width)

    def signs(self, packed: np.ndarray) -> np.ndarray:
        return np.unpackbits(packed, axis=1, bitorder="little")[:, : self.width].astype(bool)

    def keys(self, packed: np.ndarray) -> np.ndarray:
        signs = self.signs(packed)
        return np.stack([signs[:, p] @ self.powers for p in self.picks], 1)

    def most_apart(self, threshold: float, deviates: float) -> float:
        """The greatest number of differing bits that a pair at the threshold shows within the confidence bound."""
        p = math.acos(min(1.0, threshold)) / math.pi
        return self.width * (p + deviates * math.sqrt(p * (1 - p) / self.width)) + 1e-9

    def estimate(self, packed: np.ndarray, factor: np.ndarray, turned: np.ndarray) -> np.ndarray:
        """Unbiased estimates of the cosines of coded vectors (rows) with turned ones (columns)."""
        code = np.where(self.signs(packed), 1.0, -1.0) / math.sqrt(self.width)
        return (code @ turned.T) / factor[:, None]

    def slack(self, factor: np.ndarray, deviates: float) -> np.ndarray:
        return deviates * np.sqrt(np.maximum(1 - factor**2, 0) / factor**2 / max(1, self.width - 1))


def tables_for(rows: int, threshold: float, recall: float, bucket_rows: int) -> tuple[int, int]:
    """(bits, tables): buckets of about a quarter of bucket_rows, and enough tables for the recall at the threshold."""
    bits = max(1, math.ceil(math.log2(max(2.0, 4 * rows / bucket_rows))))
    meet = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(1 - recall) / math.log(1 - meet)) if meet < 1 else 1)


class _Unit:
    """One block pair of a bucket: which pairs of it may link, by their codes, and met in no earlier table."""

    def __init__(self, unit: pa.Table, coders: dict[int, Coder], tables: int, bits: int, threshold: float, deviates: float):
        dims, self.table = unit["dims"][0].as_py(), unit["tab"][0].as_py()
        if dims not in coders:
            coders[dims] = Coder(dims, tables, bits)
        self.coder = coders[dims]
        self.packed = np.frombuffer(b"".join(unit["code"].to_pylist()), np.uint8).reshape(unit.num_rows, -1)
        self.most = self.coder.most_apart(threshold, deviates)
        self.keys = self.coder.keys(self.packed)
        low, high, mine = unit["low"][0].as_py(), unit["high"][0].as_py(), unit["block"].to_numpy()
        self.whole = low == high
        every = np.arange(unit.num_rows)
        self.rows, self.cols = (every, every) if self.whole else (every[mine == low], every[mine == high])
        size = -(-self.packed.shape[1] // 8) * 8
        wide = np.zeros((unit.num_rows, size), np.uint8)
        wide[:, : self.packed.shape[1]] = self.packed
        self.words = wide.view(np.uint64)

    def pairs(self):
        """Blocks of candidate pairs (i, j)."""
        for a in range(0, len(self.rows), 256):
            r = self.rows[a : a + 256]
            apart = np.zeros((len(r), len(self.cols)), np.uint16)
            for w in range(self.words.shape[1]):
                apart += np.bitwise_count(self.words[r, w][:, None] ^ self.words[self.cols, w][None, :])
            i, j = np.nonzero(apart <= self.most)
            i, j = r[i], self.cols[j]
            if self.whole:
                i, j = i[i < j], j[i < j]
            for at in range(0, len(i), 1 << 20):
                p, q = i[at : at + (1 << 20)], j[at : at + (1 << 20)]
                if self.table and len(p):
                    fresh = ~(self.keys[p, : self.table] == self.keys[q, : self.table]).any(1)
                    p, q = p[fresh], q[fresh]
                if len(p):
                    yield p, q


PLACE = ["dims", "tab", "key", "low", "high"]


def _screen(tables: int, bits: int, threshold: float, deviates: float):
    coders: dict[int, Coder] = {}

    def run(unit: pa.Table) -> pa.Table:
        """The documents of a unit that may have a partner in it."""
        u = _Unit(unit, coders, tables, bits, threshold, deviates)
        some = np.zeros(unit.num_rows, bool)
        for i, j in u.pairs():
            some[i] = some[j] = True
        return unit.filter(pa.array(some)).select(["rep", "fp1", *PLACE, "block"])

    return run


def _compare(tables: int, bits: int, threshold: float, deviates: float, kind: str):
    coders: dict[int, Coder] = {}

    def run(unit: pa.Table) -> pa.Table:
        """(a, fa, n): links of a document; (a, fa, b, fb): a forest of what is linked."""
        u = _Unit(unit, coders, tables, bits, threshold, deviates)
        n, weight = unit.num_rows, unit["weight"].to_numpy()
        ids, marks = unit["rep"].to_numpy(), unit["fp1"].to_numpy()
        x = _units(np.frombuffer(b"".join(unit["vector"].to_pylist()), kind).reshape(n, -1))
        turned, factor = u.coder.turned(x), unit["factor"].to_numpy()
        code, slack = np.where(u.coder.signs(u.packed), 1.0, -1.0) / math.sqrt(u.coder.width), u.coder.slack(factor, deviates)
        links, root, forest = np.zeros(n, np.int64), list(range(n)), []

        def top(k: int) -> int:
            while root[k] != k:
                root[k] = root[root[k]]
                k = root[k]
            return k

        tops = np.arange(n)
        for i, j in u.pairs():
            for at in range(0, len(i), 1 << 15):
                p, q = i[at : at + (1 << 15)], j[at : at + (1 << 15)]
                near = np.einsum("ij,ij->i", code[p], turned[q]) / factor[p] + slack[p] >= threshold
                p, q = p[near], q[near]
                near = np.einsum("ij,ij->i", x[p], x[q]) >= threshold
                p, q = p[near], q[near]
                np.add.at(links, p, weight[q])
                np.add.at(links, q, weight[p])
                apart = tops[p] != tops[q]
                for a, b in zip(p[apart].tolist(), q[apart].tolist()):
                    a, b = top(a), top(b)
                    if a != b:
                        root[b] = a
                        forest.append((a, b))
                if apart.any():
                    tops = np.array([top(k) for k in range(n)])
        some = np.flatnonzero(links)
        f, g = (np.array([e[k] for e in forest], np.int64) for k in (0, 1))
        none = [None] * len(some)
        return pa.table({
            "a": pa.array(np.concatenate([ids[some], ids[f]]), pa.int64()), "fa": pa.array(np.concatenate([marks[some], marks[f]]), pa.int64()),
            "b": pa.array([*none, *ids[g].tolist()], pa.int64()), "fb": pa.array([*none, *marks[g].tolist()], pa.int64()),
            "n": pa.array([*links[some].tolist(), *[0] * len(forest)], pa.int64()),
        })

    return run


def _units(full: np.ndarray) -> np.ndarray:
    """Rows of length 1; neither overflow nor underflow in the norms."""
    full = full.astype(np.float64)
    full = full / np.abs(full).max(1, keepdims=True)
    return full / np.linalg.norm(full, axis=1, keepdims=True)


def stored_codes(fit: DataFrame, kind: str, tables: int, bits: int) -> DataFrame:
    """fit(vec_id, fp1, fp2, embedding) -> vec_id, fp1, fp2, dims, code, factor, vector: the table of codes, one row a vector, written once."""

    def run(batches):
        coders: dict[int, Coder] = {}
        for batch in batches:
            lengths = batch.column("embedding").value_lengths().to_numpy()
            for dims in np.unique(lengths).tolist():
                part = batch.take(pa.array(np.flatnonzero(lengths == dims)))
                full = part.column("embedding").flatten().to_numpy(zero_copy_only=False).astype(kind).reshape(part.num_rows, dims)
                if dims not in coders:
                    coders[dims] = Coder(dims, tables, bits)
                code, factor = coders[dims].code(_units(full))
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c) for c in ("vec_id", "fp1", "fp2")), pa.array(np.full(part.num_rows, dims, np.int32)), pa.array([x.tobytes() for x in code], pa.binary()), pa.array(factor), pa.array([x.tobytes() for x in full], pa.binary())],
                    ["vec_id", "fp1", "fp2", "dims", "code", "factor", "vector"],
                )

    return written(fit.mapInArrow(tidy(run), "vec_id bigint, fp1 bigint, fp2 bigint, dims int, code binary, factor double, vector binary"), "embedding-codes")


def link_embeddings(vectors: DataFrame, threshold: float = 0.95, recall: float = 0.995, bucket_rows: int = 8192, deviates: float = 4.0, listed: int = 1_000_000) -> DataFrame:
    """vectors(vec_id, embedding) -> vec_id, n_links, component_id, kept."""
    field = vectors.schema["embedding"].dataType
    single = isinstance(field, ArrayType) and isinstance(field.elementType, FloatType)  # kept as they are: each is a double, too
    rows = only(vectors, vec_id="bigint", embedding="array<float>" if single else "array<double>")
    v = F.col("embedding")
    whole = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    fit = F.coalesce(F.col("vec_id").isNotNull() & (F.size(v) > 0) & whole, F.lit(False))
    marks = rows.select("vec_id", "embedding", F.when(fit, F.xxhash64(v)).alias("fp1"), F.when(fit, F.xxhash64(v, F.lit(1))).alias("fp2"))
    size = rows.count()
    bits, tables = tables_for(max(1, size), threshold, recall, bucket_rows)
    options = (tables, bits, threshold, deviates)
    codes = stored_codes(marks.where("fp1 is not null"), "<f4" if single else "<f8", tables, bits)
    # exact copies are a class: its least id, its number of rows and its code
    classes = written(codes.groupBy("fp1", "fp2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"), F.first("dims").alias("dims"), F.first("code").alias("code")), "embedding-classes")

    def keyed(batches):
        coders: dict[int, Coder] = {}
        for batch in batches:
            lengths = batch.column("dims").to_numpy()
            for dims in np.unique(lengths).tolist():
                part = batch.take(pa.array(np.flatnonzero(lengths == dims)))
                if dims not in coders:
                    coders[dims] = Coder(dims, tables, bits)
                keys = coders[dims].keys(np.frombuffer(b"".join(part.column("code").to_pylist()), np.uint8).reshape(part.num_rows, -1))
                yield part.append_column("keys", pa.array(list(keys), pa.list_(pa.int64())))

    keyed_rows = classes.select("rep", "fp1", "dims", "code").mapInArrow(tidy(keyed), "rep bigint, fp1 bigint, dims int, code binary, keys array<bigint>")
    spread = keyed_rows.select("rep", "fp1", "dims", "code", F.posexplode("keys").alias("tab", "key"))
    held = spread.groupBy("dims", "tab", "key").agg(F.count("*").alias("rows"))
    large = held.where(F.col("rows") > bucket_rows).select("dims", "tab", "key", F.ceil(F.col("rows") * 2 / bucket_rows).cast("bigint").alias("blocks"))
    large = written(large, "embedding-large")
    if large.isEmpty():
        cut = spread.withColumn("blocks", F.lit(1).cast("bigint"))
    else:  # a row for bucket_rows vectors of a table at most; of checked size
        side = F.broadcast(large) if large.count() <= listed else large
        cut = spread.join(side, ["dims", "tab", "key"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("bigint")))
    cut = cut.withColumn("block", F.pmod(F.xxhash64("rep", "fp1"), F.col("blocks"))).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)))
    units = cut.select("rep", "fp1", "code", "dims", "tab", "key", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block")
    shape = "rep bigint, fp1 bigint, dims int, tab int, key bigint, low bigint, high bigint, block bigint"
    asked = written(units.groupBy(*PLACE).applyInArrow(_screen(*options), shape), "embedding-asked")
    # vectors and factors for these only
    who = classes.select("fp1", "rep", "weight").join(asked.select("rep", "fp1").distinct(), ["rep", "fp1"])
    store = codes.select(F.col("vec_id").alias("rep"), "fp1", "code", "factor", "vector")
    fetched = store.join(F.broadcast(who) if who.count() <= listed else who, ["rep", "fp1"]).dropDuplicates(["rep", "fp1"])
    met = asked.join(fetched, ["rep", "fp1"]).groupBy(*PLACE).applyInArrow(_compare(*options, "<f4" if single else "<f8"), "a bigint, fa bigint, b bigint, fb bigint, n bigint")
    met = written(met, "embedding-links")
    links = met.where("b is null").groupBy("a", "fa").agg(F.sum("n").alias("n"))
    # a class is told apart by its id and its mark: ids may be repeated
    joined = components(met.where("b is not null").select(F.struct(F.col("a").alias("id"), F.col("fa").alias("mark")).alias("a"), F.struct(F.col("b").alias("id"), F.col("fb").alias("mark")).alias("b")))
    joined = joined.select(F.col("node.id").alias("rep"), F.col("node.mark").alias("fp1"), F.col("component.id").alias("component"))
    by_class = (
        classes.select("fp1", "fp2", "rep", "weight")
        .join(links.withColumnsRenamed({"a": "rep", "fa": "fp1"}), ["rep", "fp1"], "left")
        .join(joined, ["rep", "fp1"], "left")
        .select("fp1", "fp2", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    )
    out = marks.select("vec_id", "fp1", "fp2").join(by_class, ["fp1", "fp2"], "left").withColumn("component_id", F.coalesce("component_id", "vec_id"))
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), "component_id", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)).alias("kept"))
