"""Approximate nearest neighbours by multi-index hashing of learned binary codes.

Vectors are centred, projected on their leading directions and rotated so that quantising to signs
loses least (an alternation of signs and an orthogonal fit), learned on a bounded sample. A code's
64 bits are cut into substrings, each indexed in a table from its value to the rows that have it.
A query probes, in each table, all values within the radius that the pigeonhole leaves to a substring,
which retrieves every row within its Hamming radius; codes are compared whole, and rows within the
radius are reranked by their exact distance. Radii are chosen per query from the distances to the
sample's codes, so that a given share of rows is retrieved.

Rows stay where they are: every task indexes its own rows, in bounded batches, and answers a broadcast
block of queries (bounded; more queries are further blocks) with its nearest ones.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from meshspan.llm.common import stored

BITS = 64
_PIECES = 8  # substrings of 8 bits


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, x) of the rows that take part: not null or zero, no null or non-finite component."""
    x = F.col("embedding").cast("array<double>")
    bad = F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    return vectors.where(F.col("vec_id").isNotNull() & x.isNotNull() & ~bad & F.exists(x, lambda v: v != 0)).select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x"))


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Rows of a list column as a matrix; an error unless all lists are equally long and none is null."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(column):
        return np.zeros((0, 0))
    flat = column.flatten()
    sizes = np.asarray(column.value_lengths().fill_null(-1))
    if flat.null_count or (sizes != sizes[0]).any() or sizes[0] < 0:
        raise ValueError("vectors of unequal lengths, or with nulls")
    return np.asarray(flat, np.float64).reshape(len(column), -1)


def learn_rotation(sample: np.ndarray, bits: int = BITS, rounds: int = 40, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """(mean, projection): codes are the signs of (x - mean) @ projection. With fewer dimensions than
    bits the remaining bits come from further random rotations of the same directions."""
    mean = sample.mean(0)
    x = sample - mean
    _, basis = np.linalg.eigh(x.T @ x)
    basis = basis[:, ::-1]
    random = np.random.default_rng(seed)
    blocks, left = [], bits
    while left > 0:
        k = min(left, basis.shape[1])
        v = x @ basis[:, :k]
        rotation = np.linalg.qr(random.standard_normal((k, k)))[0]
        for _ in range(rounds):
            u, _, w = np.linalg.svd(np.sign(v @ rotation).T @ v)
            rotation = (u @ w).T
        blocks.append(basis[:, :k] @ rotation)
        left -= k
    return mean, np.hstack(blocks)


def encode(x: np.ndarray, mean: np.ndarray, projection: np.ndarray) -> np.ndarray:
    """Binary codes as unsigned 64-bit integers."""
    positive = ((x - mean) @ projection) > 0
    return np.packbits(positive, axis=1, bitorder="little").view("<u8").ravel()


class SubstringIndex:
    """Tables from each substring's value to the rows of one batch."""

    def __init__(self, codes: np.ndarray):
        self.codes = codes
        self.parts = codes.view(np.uint8).reshape(-1, _PIECES)
        self.tables = []
        for j in range(_PIECES):
            order = np.argsort(self.parts[:, j], kind="stable")
            self.tables.append((order, np.searchsorted(self.parts[order, j], np.arange(257))))

    def within(self, code: np.uint64, radius: int) -> np.ndarray:
        """All rows within the Hamming radius: some substring differs by at most radius // pieces, and
        those after the first (radius % pieces + 1) by one less."""
        found = np.zeros(len(self.codes), bool)
        parts = np.array([code], "<u8").view(np.uint8)
        whole, more = divmod(radius, _PIECES)
        for j, (order, starts) in enumerate(self.tables):
            reach = whole if j <= more else whole - 1
            if reach < 0:
                continue
            near = np.flatnonzero(np.bitwise_count(_BYTES ^ parts[j]) <= reach)
            for value in near[starts[near + 1] > starts[near]]:
                found[order[starts[value] : starts[value + 1]]] = True
        rows = np.flatnonzero(found)
        return rows[np.bitwise_count(self.codes[rows] ^ code) <= radius]


_BYTES = np.arange(256, dtype=np.uint8)


def radii(codes: np.ndarray, sample_codes: np.ndarray, share: float) -> np.ndarray:
    """For each query the smallest radius that holds at least ``share`` of the sample."""
    out = np.empty(len(codes), np.int64)
    for i, code in enumerate(codes):
        d = np.sort(np.bitwise_count(sample_codes ^ code))
        out[i] = d[min(len(d) - 1, int(np.ceil(share * len(d))))]
    return out


_FOUND = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])


def _nearest(ids: np.ndarray, x: np.ndarray, query: np.ndarray, own_id: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    keep = ids != own_id
    ids, x = ids[keep], x[keep]
    d = np.sqrt(((x - query) ** 2).sum(1))
    order = np.lexsort((ids, d))[:k]
    return ids[order], d[order]


def nearest(
    vectors: DataFrame, queries: DataFrame, k: int = 10, share: float = 0.35, sample: int = 20_000, query_block: int = 8192, batch_rows: int = 50_000
) -> DataFrame:
    """The ``k`` rows of ``vectors(vec_id, embedding)`` nearest to each row of ``queries`` (same columns),
    by Euclidean distance in double precision: query_id, rank (from 1), vec_id, score; ties go to the
    smaller vec_id. A query's own id is not a candidate.

    ``share``: share of all rows within a query's radius, the knob between work and recall; a query
    whose task-local radius holds fewer than ``k`` rows takes all the task's rows. ``sample``: bound of
    the rows from which rotation and radii are learned. Null, zero and non-finite vectors and rows without vec_id take no part;
    repeated rows are candidates as often as they come; vectors of unequal lengths raise an error; empty tables give no rows.
    """
    spark = vectors.sparkSession
    rows = usable(vectors)
    hashed = stored(rows, "vectors")
    total = hashed.count()
    fit = hashed.where(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, total // sample))) == 0) if total > 2 * sample else hashed
    learned = matrix(fit.select("vec_id", "x").limit(2 * sample).toArrow().sort_by("vec_id")["x"])
    asked = stored(usable(queries).distinct(), "queries")
    blocks = max(1, -(-asked.count() // query_block))
    parts = []
    if len(learned):
        mean, projection = learn_rotation(learned)
        learned_codes = encode(learned[:4096], mean, projection)
    for block in range(blocks if len(learned) else 0):
        own = asked.where(F.pmod(F.xxhash64(F.lit(11), "vec_id"), F.lit(blocks)) == block).toArrow().sort_by("vec_id")
        if not own.num_rows:
            continue
        q_ids, q = np.asarray(own["vec_id"]), matrix(own["x"])
        q_codes = encode(q, mean, projection)
        reach = radii(q_codes, learned_codes, share)
        shared = spark.sparkContext.broadcast((q_ids, q, q_codes, reach, mean, projection))

        def answer(ids, x, shared=shared):
            q_ids, q, q_codes, reach, mean, projection = shared.value
            index = SubstringIndex(encode(x, mean, projection))
            out = []
            for i in range(len(q_ids)):
                near = index.within(q_codes[i], int(reach[i]))
                if len(near) <= k:
                    near = np.arange(len(ids))
                best, d = _nearest(ids[near], x[near], q[i], q_ids[i], k)
                out.append((np.full(len(best), q_ids[i]), best, d))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], schema=_FOUND)

        def run(batches, answer=answer):
            ids, x, held = [], [], 0
            for batch in batches:
                if batch.num_rows:
                    ids.append(np.asarray(batch.column("vec_id")))
                    x.append(matrix(batch.column("x")))
                    held += batch.num_rows
                if held >= batch_rows:
                    yield answer(np.concatenate(ids), np.vstack(x))
                    ids, x, held = [], [], 0
            if held:
                yield answer(np.concatenate(ids), np.vstack(x))

        parts.append(hashed.mapInArrow(run, "query_id long, vec_id long, score double"))
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    found = parts[0]
    for part in parts[1:]:
        found = found.union(part)
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.withColumn("rank", F.row_number().over(order).cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def recall(found: DataFrame, vectors: DataFrame, sample: int = 64, k: int = 10) -> float:
    """Share of the true ``k`` nearest that ``found`` holds, over a bounded sample of its queries,
    by brute force over all rows."""
    ids = [r[0] for r in found.select("query_id").distinct().orderBy(F.xxhash64("query_id")).limit(sample).collect()]
    if not ids:
        return 1.0
    rows = usable(vectors)
    asked = rows.where(F.col("vec_id").isin(ids)).toArrow()
    q_ids, q = np.asarray(asked["vec_id"]), matrix(asked["x"])

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                all_ids, x = np.asarray(batch.column("vec_id")), matrix(batch.column("x"))
                out = [(np.full(min(k, (all_ids != i).sum()), i), *_nearest(all_ids, x, v, i, k)) for i, v in zip(q_ids, q, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], schema=_FOUND)

    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    true = rows.mapInArrow(run, "query_id long, vec_id long, score double").withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    hits = true.join(found.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_semi").count()
    return hits / max(1, true.count())
