"""Feature views: every method's input is (sample_id, features ARRAY<DOUBLE>)."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructField, StructType

from meshspan.functions.vectors import mat_literal, mat_vec
from meshspan.operators import moments, nodes
from meshspan.sources.tables import load_table


def to_features(df: DataFrame, sample_id: str, columns: list[str]) -> DataFrame:
    """Numeric, decimal and boolean columns as one vector per row."""
    casts = [F.col(c).cast("int").cast("double") if dict(df.dtypes)[c] == "boolean" else F.col(c).cast("double") for c in columns]
    return df.select(F.col(sample_id).alias("sample_id"), F.array(*casts).alias("features"))


def validated(samples: DataFrame, null_policy: str = "reject") -> DataFrame:
    """Samples of one length without nulls or NaN. ``reject`` raises if there are any, ``drop`` leaves such
    rows out, ``zero`` and ``mean`` fill entries (null vectors are dropped). Ragged vectors always raise."""
    f = F.col("features")
    holes = F.exists(f, lambda v: v.isNull() | F.isnan(v))
    low, high, bad, ragged = samples.agg(
        F.min(F.when(f.isNotNull(), F.size(f))), F.max(F.when(f.isNotNull(), F.size(f))), F.count(F.when(f.isNull() | holes, 1)),
        F.max_by("sample_id", F.when(f.isNotNull(), F.size(f))),
    ).first()
    if low != high:
        raise ValueError(f"vectors of {low} to {high} entries; the longest is sample {ragged}")
    if not bad:
        return samples
    if null_policy == "reject":
        raise ValueError(f"{bad} samples hold nulls or NaN")
    there = samples.where(f.isNotNull())
    if null_policy == "drop":
        return there.where(~holes)
    if null_policy == "zero":
        return there.withColumn("features", F.transform(f, lambda v: F.when(v.isNull() | F.isnan(v), 0.0).otherwise(v)))
    if null_policy == "mean":
        each = there.select(F.posexplode("features")).where("col is not null and not isnan(col)").groupBy("pos").agg(F.avg("col").alias("m"))
        means = dict(each.collect())  # one row per dimension
        fill = F.array(*[F.lit(float(means.get(i, 0.0))) for i in range(low)])
        return there.withColumn("features", F.zip_with(f, fill, lambda v, m: F.when(v.isNull() | F.isnan(v), m).otherwise(v)))
    raise ValueError(f"unknown policy {null_policy!r}")


def embeddings(spark: SparkSession, sf_dir: str, dims: int | None = None) -> DataFrame:
    e = F.col("embedding").cast("array<double>")
    e = F.slice(e, 1, dims) if dims else e
    return load_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "label", e.alias("features"))


def linear_map(samples: DataFrame, matrix: np.ndarray, shift: np.ndarray | None = None) -> DataFrame:
    """features -> matrix @ (features - shift), in SQL expressions."""
    f = F.col("features")
    if shift is not None:
        f = F.zip_with(f, F.array(*[F.lit(float(v)) for v in shift]), lambda a, b: a - b)
    return samples.withColumn("features", mat_vec(mat_literal(matrix), f))


def spectrum(d: int, r: int, delta: float, tied: bool = False) -> np.ndarray:
    """Eigenvalues with ratio ``delta`` after the r-th: the first r fall from 1 to 0.8 (or tie), the others
    from 0.8 delta to 0.4 delta."""
    top = np.ones(r) if tied else np.linspace(1, 0.8, r)
    return np.concatenate((top, np.linspace(top[-1] * delta, top[-1] * delta / 2, d - r)))


def shaped(samples: DataFrame, r: int, delta: float, tied: bool = False) -> DataFrame:
    """Samples centred, whitened and scaled so that their covariance (over n) is exactly diagonal with
    :func:`spectrum`: the leading subspace is that of the first r axes."""
    m = moments.global_moments(samples)
    values, vectors = np.linalg.eigh(m.covariance)
    if values[0] < 1e-10 * values[-1]:
        raise ValueError("the samples do not span their dimension")
    scale = np.sqrt(spectrum(m.d, r, delta, tied))
    return linear_map(samples, scale[:, None] * (vectors / np.sqrt(values)).T, m.mean)


def standardized(samples: DataFrame, zero_variance: str = "drop") -> DataFrame:
    """Zero mean and unit variance per entry. Entries without variance are dropped, kept as zeros, or an error."""
    m = moments.global_moments(samples)
    spread = np.sqrt(np.maximum(np.diag(m.covariance), 0))
    flat = spread <= 1e-12 * max(1.0, spread.max())
    if flat.any() and zero_variance == "error":
        raise ValueError(f"no variance in entries {np.flatnonzero(flat).tolist()}")
    keep = np.flatnonzero(~flat) if zero_variance == "drop" else np.arange(m.d)
    inv = np.where(flat, 0.0, 1 / np.where(flat, 1.0, spread))
    out = F.array(*[(F.element_at("features", int(i) + 1) - float(m.mean[i])) * float(inv[i]) for i in keep])
    return samples.withColumn("features", out)


def line_aggregates(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """Eight aggregates of lineitem per order, part or supplier: count, quantity, price, discounted price,
    charge, mean discount, mean tax, largest quantity."""
    price, disc, tax = F.col("l_extendedprice"), F.col("l_discount"), F.col("l_tax")
    agg = load_table(spark, sf_dir, "lineitem").groupBy(F.col(key).alias("sample_id")).agg(
        F.count("*").cast("double").alias("f0"), F.sum("l_quantity").alias("f1"), F.sum(price).alias("f2"), F.sum(price * (1 - disc)).alias("f3"),
        F.sum(price * (1 - disc) * (1 + tax)).alias("f4"), F.avg(disc).alias("f5"), F.avg(tax).alias("f6"), F.max("l_quantity").alias("f7"),
    )
    return to_features(agg, "sample_id", [f"f{i}" for i in range(8)])


def line_numeric(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load_table(spark, sf_dir, "lineitem").withColumn("sample_id", F.col("l_orderkey") * 8 + F.col("l_linenumber"))
    return to_features(t, "sample_id", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"])


def bucket_of(token: Column, buckets: int) -> Column:
    """md5 bucket that other engines reproduce."""
    return (F.conv(F.substring(F.md5(token), 1, 8), 16, 10).cast("long") % buckets).cast("int")


_DENSE_BYTES = 8 << 20  # of the vectors that leave a task at a time
_WORDS = 1 << 18  # whose buckets a task remembers


class _Buckets(dict):
    """Buckets of the words met so far; a new word's is computed."""

    def __init__(self, buckets: int):
        super().__init__()
        self.buckets = buckets

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _WORDS:
            self.clear()
        out = self[word] = int.from_bytes(hashlib.md5(word, usedforsecurity=False).digest()[:4]) % self.buckets
        return out


def hashed_words(df: DataFrame, sample_id: str, text: Column, buckets: int) -> DataFrame:
    """Relative frequencies of md5-hashed lower-case tokens. A row's tokens are counted where the row lies; bags of
    equal ids, the only thing that is shuffled, are added before vectors are built, of which every row gets its id's.
    Samples without tokens or without an id are zero vectors."""
    lower = df.select(F.col(sample_id).alias("sample_id"), F.lower(F.coalesce(text, F.lit(""))).cast("binary").alias("text"))
    kind = lower.schema["sample_id"]

    def bags(batches):
        known = _Buckets(buckets)
        for batch in batches:
            at, counts = [], []
            for t in batch.column("text"):
                words = t.as_py().split()  # of bytes: at what \s stands for in SQL
                n = np.bincount(np.fromiter(map(known.__getitem__, words), np.int64, len(words)), minlength=buckets)
                own = np.flatnonzero(n)
                at.append(own.astype(np.int32))
                counts.append(n[own])
            ends = pa.array(np.cumsum([0, *map(len, at)]), pa.int32())
            lists = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate([np.zeros(0, x), *parts]), y)) for parts, x, y in ((at, np.int32, pa.int32()), (counts, np.int64, pa.int64()))]
            yield pa.RecordBatch.from_arrays([batch.column("sample_id"), *lists], ["sample_id", "at", "n"])
        known.clear()
        nodes.given_back()

    counted = lower.mapInArrow(bags, StructType([kind, StructField("at", ArrayType(IntegerType())), StructField("n", ArrayType(LongType()))]))
    spread = F.when(F.col("sample_id").isNull(), F.xxhash64("at"))  # rows without an id belong nowhere
    together = counted.repartition("sample_id", spread).sortWithinPartitions("sample_id")
    step = max(1, _DENSE_BYTES // (8 * buckets))

    def dense(batches):
        own, total, copies, kind = None, np.zeros(buckets, np.int64), 0, None
        ids, rows = [], np.zeros((step, buckets))

        def out():
            ends = pa.array(np.arange(len(ids) + 1, dtype=np.int32) * buckets)
            made = pa.RecordBatch.from_arrays([pa.array(ids, kind), pa.ListArray.from_arrays(ends, pa.array(rows[: len(ids)].ravel().copy()))], ["sample_id", "features"])
            ids.clear()
            return made

        def placed():
            share = total / max(1, total.sum()) if own is not None else 0.0
            for _ in range(copies):
                rows[len(ids)] = share
                ids.append(own)
                if len(ids) == step:
                    yield out()

        for batch in batches:
            kind, known, at, n = batch.schema.field("sample_id").type, batch.column("sample_id").to_pylist(), batch.column("at"), batch.column("n")
            ends, at, n = np.cumsum([0, *pc.list_value_length(at).to_pylist()]), np.asarray(at.flatten()), np.asarray(n.flatten())
            for i, x in enumerate(known):
                if copies and x != own:
                    yield from placed()
                    total[:], copies = 0, 0
                own, copies = x, copies + 1
                total[at[ends[i] : ends[i + 1]]] += n[ends[i] : ends[i + 1]]
        yield from placed()
        if ids:
            yield out()
        nodes.given_back()

    return together.mapInArrow(dense, StructType([kind, StructField("features", ArrayType(DoubleType()))]))


def documents_hashed(spark: SparkSession, sf_dir: str, buckets: int = 32) -> DataFrame:
    return hashed_words(load_table(spark, sf_dir, "documents"), "doc_id", F.col("text"), buckets)


def pages_hashed(spark: SparkSession, sf_dir: str, buckets: int = 64) -> DataFrame:
    return hashed_words(load_table(spark, sf_dir, "pages"), "page_id", F.regexp_replace("html", "<[^>]*>", " "), buckets)


def conversations_hashed(spark: SparkSession, sf_dir: str, buckets: int = 32) -> DataFrame:
    t = load_table(spark, sf_dir, "conversations").withColumn("sample_id", F.col("conv_id") * 1000 + F.col("turn"))
    return hashed_words(t, "sample_id", F.col("text"), buckets)


def user_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load_table(spark, sf_dir, "events").select("user_id", F.hour("ts").alias("h"))
    wide = e.groupBy("user_id").pivot("h", list(range(24))).count().na.fill(0)
    return to_features(wide, "user_id", [str(h) for h in range(24)])


def gaussian(spark: SparkSession, nodes: int, per_node: int, eigenvalues: np.ndarray, seed: int = 1) -> DataFrame:
    """Independent normal samples with a diagonal covariance; has its own node column."""
    scale = np.sqrt(eigenvalues)
    row = F.array(*[F.randn(seed * 1000 + i) * float(s) for i, s in enumerate(scale)])
    return spark.range(nodes * per_node, numPartitions=max(1, min(nodes, 64))).select(F.col("id").alias("sample_id"), (F.col("id") % nodes).cast("int").alias("node"), row.alias("features"))
