"""What a node's covariance does to a basis, wherever its numbers lie.

One scan turns the samples into *pieces* of raw moments. A task keeps a node's rows as they are while it has
fewer of them than features, and folds them into their sum of outer products beyond, so that a piece is never
larger than the rows it stands for; what a task holds is flushed at a byte budget. Pieces of one node are
folded again after a shuffle by node, until every node holds the smaller of its rows and a d x d matrix.
Centring is a correction of rank two with the nodes' sums and costs no second scan.

The iterations ask only for products, so they run alike on three kinds of node moments:
:class:`LocalNodes` (in the memory of one task), :class:`SpreadNodes` (pieces stay in a stored table; a step
broadcasts the bases, whose size is checked, and shuffles nothing) and :class:`SampleNodes` (one node, one scan of
the samples per product).
"""

from __future__ import annotations

import contextlib
import ctypes
import dataclasses
import gc
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.functions.linalg import anchor_scale, leading
from meshspan.sources.tables import stored

PIECE_BYTES = 4 << 20
ROWS_BYTES = 384 << 10  # of rows in a piece: the JVM gathers arrays of half a region and more late, and its heap grows
FLUSH_BYTES = 256 << 20
TASK_BYTES = 32 << 20
SMALL_BYTES = 1 << 18
DENSE_BYTES = 256 << 20  # of a d x d matrix in one place
#: Rows that are mostly zeros shrink well; a reader holds a row group at a time, whose size is looked at after every piece.
_FILES = {"compression": "zstd", "parquet.block.size": str(2 << 20), "parquet.block.size.row.check.min": "1"}
PIECES = "node int, low int, k int, n long, total binary, body binary"
_PIECE = pa.schema([("node", pa.int32()), ("low", pa.int32()), ("k", pa.int32()), ("n", pa.int64()), ("total", pa.binary()), ("body", pa.binary())])


def given_back() -> None:
    """Memory that this process no longer uses goes back to the machine: a worker waits for its next task beside
    others that need it."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def vectors_of(column: pa.Array, d: int | None = None) -> np.ndarray:
    """Rows of a list column as a matrix. Null vectors, null entries and unequal lengths are errors: see
    ``features.validated`` for ways to mend them."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if column.null_count:
        raise ValueError("a sample's vector is null")
    lengths = np.diff(np.asarray(column.offsets)) if len(column) else np.zeros(0, int)
    width = d if d is not None else int(lengths[0]) if len(lengths) else 0
    if (lengths != width).any():
        raise ValueError(f"vectors of {lengths.min()} to {lengths.max()} entries, not {width}")
    values = column.flatten()
    if values.null_count:
        raise ValueError("a sample's vector holds a null")
    return np.asarray(values, np.float64).reshape(len(column), width)


def _blocks(d: int) -> int:
    return max(1, PIECE_BYTES // (8 * d))


def _emitted(node: int, d: int, rows: np.ndarray | None, dense: np.ndarray | None, n: int, total: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Pieces of a node: rows (low = -1), then blocks of its matrix from row ``low``; n and sums of what the
    matrix holds go with its first block, those of rows with the rows."""
    step, out = _blocks(d), []
    if rows is not None:
        few = max(1, ROWS_BYTES // (8 * d))
        for at in range(0, len(rows), few):
            own = rows[at : at + few]
            out.append((-1, len(own), len(own), own.sum(0), own))
    if dense is not None:
        for at in range(0, d, step):
            out.append((at, min(step, d - at), n if at == 0 else 0, total if at == 0 else None, dense[at : at + step]))
    for low, k, own_n, own_total, body in out:
        yield pa.RecordBatch.from_arrays(
            [pa.array([v], t) for v, t in ((node, pa.int32()), (low, pa.int32()), (k, pa.int32()), (own_n, pa.int64()), (None if own_total is None else own_total.tobytes(), pa.binary()), (np.ascontiguousarray(body).tobytes(), pa.binary()))],
            schema=_PIECE,
        )


class _Folding:
    """Rows and matrices of the nodes that a task has met, within a byte budget."""

    def __init__(self, d: int, budget: int, keep: bool = True):
        self.d, self.budget, self.keep, self.held, self.size = d, budget, keep, {}, 0

    def add_rows(self, node: int, own: np.ndarray) -> None:
        state = self.held.setdefault(node, [[], 0, None, 0, np.zeros(self.d)])
        state[0].append(own)
        state[1] += len(own)
        self.size += own.nbytes
        if state[1] >= self.d:
            self._fold(state)

    def add_dense(self, node: int, low: int, block: np.ndarray, n: int, total: np.ndarray | None) -> None:
        state = self.held.setdefault(node, [[], 0, None, 0, np.zeros(self.d)])
        self._room(state)
        state[2][low : low + len(block)] += block
        state[3] += n
        if total is not None:
            state[4] += total

    def _room(self, state: list) -> None:
        if state[2] is None:
            state[2] = np.zeros((self.d, self.d))
            self.size += state[2].nbytes

    def _fold(self, state: list) -> None:
        x = np.concatenate(state[0])
        self._room(state)
        state[2] += x.T @ x
        state[3] += len(x)
        state[4] += x.sum(0)
        self.size -= x.nbytes
        state[0], state[1] = [], 0

    def flush(self, only_full: bool = False) -> Iterator[pa.RecordBatch]:
        if only_full and self.size <= self.budget:
            return
        for node, state in self.held.items():
            if state[0] and not self.keep:
                self._fold(state)
            rows, _, dense, n, total = state
            yield from _emitted(node, self.d, np.concatenate(rows) if rows else None, dense, n, total)
        self.held, self.size = {}, 0


def dimension(samples: DataFrame) -> int:
    row = samples.select(F.size("features").alias("d")).limit(1).collect()
    if not row:
        raise ValueError("no samples")
    return row[0]["d"]


def raw_pieces(samples: DataFrame, d: int, keep: bool = True) -> DataFrame:
    """Every task's pieces of ``samples(node, features)``; without ``keep`` rows are folded however few."""

    def run(batches):
        state = _Folding(d, FLUSH_BYTES, keep)
        for batch in batches:
            if not batch.num_rows:
                continue
            x, node = vectors_of(batch.column("features"), d), np.asarray(batch.column("node"))
            order = np.argsort(node, kind="stable")
            starts = np.flatnonzero(np.concatenate(([True], np.diff(node[order]) != 0)))
            for own in np.split(order, starts[1:]):
                state.add_rows(int(node[own[0]]), x[own])
            yield from state.flush(only_full=True)
        yield from state.flush()
        given_back()

    return samples.select(F.col("node").cast("int").alias("node"), F.col("features").cast("array<double>").alias("features")).where("node is not null").mapInArrow(run, PIECES)


def _folded(pieces: DataFrame, d: int) -> DataFrame:
    """Pieces of equal nodes that lie together, folded; a task holds one node's at a time."""

    def run(batches):
        state, now = _Folding(d, 1 << 62), None
        for batch in batches:
            for node, low, k, n, total, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "n", "total", "body")), strict=True):
                if node != now:
                    yield from state.flush()
                    now = node
                block = np.frombuffer(body).reshape(k, d)
                if low < 0:
                    state.add_rows(node, block)
                else:
                    state.add_dense(node, low, block, n, None if total is None else np.frombuffer(total))
        yield from state.flush()

    return pieces.mapInArrow(run, PIECES)


def added(pieces: DataFrame, d: int) -> DataFrame:
    """Sums of matrix blocks at equal places; a task holds one place's at a time."""

    def run(batches):
        now, kept = None, None

        def out():
            node, low = now
            n, total, block = kept
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in ((node, pa.int32()), (low, pa.int32()), (len(block), pa.int32()), (n, pa.int64()), (total.tobytes() if low == 0 else None, pa.binary()), (block.tobytes(), pa.binary()))], schema=_PIECE)

        for batch in batches:
            for node, low, k, n, total, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "n", "total", "body")), strict=True):
                if (node, low) != now:
                    if now is not None:
                        yield out()
                    now, kept = (node, low), [0, np.zeros(d), np.zeros((k, d))]
                kept[0] += n
                if total is not None:
                    kept[1] = kept[1] + np.frombuffer(total)
                kept[2] += np.frombuffer(body).reshape(k, d)
        if now is not None:
            yield out()

    return pieces.mapInArrow(run, PIECES)


@dataclasses.dataclass
class PieceTable:
    """Stored pieces of node moments, and the nodes' row counts and sums (N x d numbers, checked)."""

    df: DataFrame
    n: int
    d: int
    rows: np.ndarray
    sums: np.ndarray
    bytes: int
    center: str = "exact"
    normalizer: str = "n"
    local_scale: str = "sum"
    dense: bool = True  # whether any node's rows are folded
    scale: float = 1.0  # of all moments

    @property
    def mean(self) -> np.ndarray:
        return self.sums.sum(0) / max(1, self.rows.sum()) if self.center == "exact" else np.zeros(self.d)

    @property
    def factors(self) -> np.ndarray:
        """What each node's moments are multiplied with. ``sum`` makes the nodes' mean the covariance; ``mean``
        divides each node by its own rows (equal weight for nodes of unequal size)."""
        if self.local_scale == "mean":
            return np.where(self.rows > 0, self.scale / np.maximum(1, self.rows), 0.0)
        if self.local_scale != "sum":
            raise ValueError(f"unknown scale {self.local_scale!r}")
        total = self.rows.sum()
        return np.full(self.n, {"n": self.n / max(1, total), "n-1": self.n / max(1, total - 1), "none": 1.0}[self.normalizer] * self.scale)

    def coarser(self, n: int) -> PieceTable:
        """Of a network whose node k holds what the nodes k, k + n, k + 2n, ... hold: the same pieces."""
        if self.n % n:
            raise ValueError(f"{n} nodes do not divide {self.n}")
        return dataclasses.replace(
            self, df=self.df.withColumn("node", F.pmod("node", F.lit(n)).cast("int")), n=n, rows=self.rows.reshape(-1, n).sum(0), sums=self.sums.reshape(-1, n, self.d).sum(0)
        )

    @property
    def compact(self) -> int:
        """Bytes of :class:`CompactNodes` of this table."""
        return min(8 * self.n * _panel_size(self.d), self.bytes if not self.dense else 1 << 62)

    def leading(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        """The first r + 1 eigenvalues of the covariance in falling order (fewer if there are no more), and the first
        r eigenvectors. Tasks add up panels of their pieces' half matrices, whose bytes are checked; one task puts
        them together and decomposes their sum."""
        d, mean, f = self.d, self.mean, self.factors
        if d * d * 8 > DENSE_BYTES:
            raise ValueError("the covariance exceeds the budget: give the truth as a basis")
        sums, weight, n = (f[:, None] * self.sums).sum(0), (f * self.rows).sum(), self.n
        places, schema = dict(_panels(d)), pa.schema([("low", pa.int32()), ("row", pa.int32()), ("body", pa.binary())])

        def added_up(batches):
            panels, few = {a: np.zeros((w, d - a)) for a, w in places.items()}, []
            for node, low, block, _, _ in _pieces_of(batches, d):
                if low >= 0:
                    _add_block(panels, low, block, f[node])
                    continue
                few.append(block * np.sqrt(f[node]))
                if sum(map(len, few)) >= 4 * PANEL:
                    _fold_rows(panels, np.concatenate(few))
                    few = []
            if few:
                _fold_rows(panels, np.concatenate(few))
            for a in list(panels):
                own, few = panels.pop(a), max(1, ROWS_BYTES // (8 * (d - a)))
                for row in range(0, len(own), few):
                    yield pa.RecordBatch.from_arrays([pa.array([a], pa.int32()), pa.array([a + row], pa.int32()), pa.array([own[row : row + few].tobytes()], pa.binary())], schema=schema)
            given_back()

        def decomposed(batches):
            total = np.zeros((d, d))
            for batch in batches:
                for low, row, body in zip(batch.column("low").to_pylist(), batch.column("row").to_pylist(), batch.column("body"), strict=True):
                    block = np.frombuffer(body.as_buffer()).reshape(-1, d - low)
                    total[row : row + len(block), low:] += block
            for a, w in places.items():
                total[a + w :, a : a + w] = total[a : a + w, a + w :].T
            cross = np.outer(sums, mean)
            total -= cross
            total -= cross.T
            total += weight * np.outer(mean, mean)
            total /= n
            del cross
            given_back()
            values, vectors = np.linalg.eigh(total)
            values, vectors = values[::-1][: r + 1].tobytes(), vectors[:, ::-1][:, :r].tobytes()
            del total
            given_back()
            yield pa.RecordBatch.from_arrays([pa.array([values], pa.binary()), pa.array([vectors], pa.binary())], ["values", "vectors"])

        tasks = int(np.clip(TASK_BYTES // (8 * _panel_size(d)), 1, self.df.sparkSession.sparkContext.defaultParallelism))
        halves = self.df.coalesce(tasks).mapInArrow(added_up, "low int, row int, body binary")
        halves = halves if tasks == 1 else halves.repartition(1)
        found = halves.mapInArrow(decomposed, "values binary, vectors binary").collect()[0]
        return np.frombuffer(found["values"]), np.frombuffer(found["vectors"]).reshape(d, r)

    def local(self) -> LocalNodes:
        """All pieces in this process; their size is checked by the caller."""
        return LocalNodes.from_batches(self, self.df.toArrow().to_batches())


def node_pieces(samples: DataFrame, n: int, d: int, center: str = "exact", normalizer: str = "n", local_scale: str = "sum") -> PieceTable:
    """Pieces of ``samples(node, features)``: one scan of the samples. Nodes beyond ``n`` are an error; rows
    without a node are left out."""
    if n * d * 8 > DENSE_BYTES:
        raise ValueError("the nodes' sums exceed the budget")
    parts = stored(raw_pieces(samples, d), "pieces", **_FILES)

    def sums(key: tuple, group: pa.Table) -> pa.Table:
        totals = [np.frombuffer(t) for t in group["total"].to_pylist() if t is not None]
        low, k = np.asarray(group["low"]), np.asarray(group["k"]).astype(np.int64)
        return pa.table({
            "node": key, "n": [int(np.asarray(group["n"]).sum())], "total": pa.array([np.sum(totals, axis=0).tobytes() if totals else np.zeros(d).tobytes()], pa.binary()),
            "loose": [int(k[low < 0].sum())], "copies": [int((low == 0).sum())], "bytes": [int(k.sum()) * d * 8],
        })

    found = parts.select("node", "low", "k", "n", "total").groupBy("node").applyInArrow(sums, "node int, n long, total binary, loose long, copies long, bytes long").toArrow()
    node = np.asarray(found["node"])
    if not len(node):
        raise ValueError("no samples")
    if node.min() < 0 or node.max() >= n:
        raise ValueError("a sample's node lies outside the network")
    rows, total = np.zeros(n, np.int64), np.zeros((n, d))
    rows[node] = np.asarray(found["n"])
    total[node] = np.stack([np.frombuffer(t) for t in found["total"].to_pylist()])
    loose, copies = np.asarray(found["loose"]), np.asarray(found["copies"])
    size = int(np.asarray(found["bytes"]).sum())
    heavy = loose > d
    if heavy.any() or (copies > 1).any():
        salts = int(np.clip(loose.max() // (16 * d), 1, 256))
        tasks = max(1, min(2048, int(size // TASK_BYTES) + 1))
        many = parts.sparkSession.createDataFrame([(int(v),) for v in node[heavy]], "node int")
        rowed, blocks = parts.where("low < 0"), parts.where("low >= 0")
        if heavy.any():
            folded = rowed.join(F.broadcast(many), "node").select(*_PIECE.names).withColumn("salt", F.pmod(F.xxhash64("body"), F.lit(salts)))
            folded = _folded(folded.repartition(tasks, "node", "salt").sortWithinPartitions("node", "salt").select(*_PIECE.names), d)
            folded = stored(folded, "folded")
            blocks = blocks.union(folded.where("low >= 0"))
            rowed = rowed.join(F.broadcast(many), "node", "left_anti").select(*_PIECE.names).union(folded.where("low < 0"))
        blocks = added(blocks.repartition(tasks, "node", "low").sortWithinPartitions("node", "low"), d)
        parts = stored(blocks.union(rowed), "moments")
        size = int(parts.agg(F.sum(F.length("body"))).first()[0] or 0)
    return PieceTable(parts, n, d, rows, total, size, center, normalizer, local_scale, bool(heavy.any() or copies.any()))


# ---------------------------------------------------------------- in memory


class LocalNodes:
    """Node moments in memory: stacked matrices, or the scaled, centred rows of nodes that have few."""

    def __init__(self, matrices: np.ndarray | None = None, rows: list[np.ndarray] | None = None):
        self.matrices, self.rows = matrices, rows
        if matrices is not None:
            self.n, self.d = len(matrices), matrices.shape[1]
        else:
            self.n, self.d = len(rows), rows[0].shape[1]
        self._total: np.ndarray | None = None
        self._known: tuple[np.ndarray, np.ndarray] | None = None  # eigenvalues, and the eigenvectors asked for so far
        self._padded: np.ndarray | None = None
        if matrices is None:
            most = max(len(x) for x in rows)
            if most * len(rows) <= 2 * max(1, sum(map(len, rows))):
                self._padded = np.zeros((len(rows), most, self.d))
                for i, x in enumerate(rows):
                    self._padded[i, : len(x)] = x
                self.rows = [self._padded[i, : len(x)] for i, x in enumerate(rows)]

    @classmethod
    def from_batches(cls, table: PieceTable, batches: Iterable[pa.RecordBatch]) -> LocalNodes:
        n, d, mean, factors = table.n, table.d, table.mean, table.factors
        loose: list[list[np.ndarray]] = [[] for _ in range(n)]
        dense: dict[int, list] = {}
        for batch in batches:
            for node, low, k, own_n, total, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "n", "total", "body")), strict=True):
                block = np.frombuffer(body).reshape(k, d)
                if low < 0:
                    loose[node].append((block - mean) * np.sqrt(factors[node]))
                    continue
                state = dense.setdefault(node, [0, np.zeros(d), np.zeros((d, d))])
                state[0] += own_n
                if total is not None:
                    state[1] += np.frombuffer(total)
                state[2][low : low + k] += block
        held = [np.concatenate(x) if x else np.zeros((0, d)) for x in loose]
        if not dense and 2 * max(map(len, held)) < d:
            return cls(rows=held)
        if dense and n * d * d * 8 > 4 * DENSE_BYTES:
            raise ValueError("node matrices exceed a task's budget")
        if not dense and n * d * d * 8 > DENSE_BYTES:
            return cls(rows=held)
        out = np.stack([x.T @ x for x in held])
        for node, (own_n, total, block) in dense.items():
            cross = np.outer(total, mean)
            out[node] += factors[node] * (block - cross - cross.T + own_n * np.outer(mean, mean))
        return cls(matrices=out)

    def scaled(self, by: float) -> LocalNodes:
        """The same moments times a number; eigenvectors that are known stay known."""
        out = LocalNodes(self.matrices * by) if self.matrices is not None else LocalNodes(rows=[x * np.sqrt(by) for x in self.rows])
        if self._known is not None and by > 0:
            out._known = self._known[0] * by, self._known[1]
        return out

    def apply(self, q: np.ndarray) -> np.ndarray:
        """Every node's product with its own basis: (N, d, r), or one basis for all."""
        q = np.asarray(q)
        if self.matrices is not None:
            return self.matrices @ q
        if self._padded is not None:
            return np.swapaxes(self._padded, 1, 2) @ (self._padded @ q)
        q = np.broadcast_to(q, (self.n, *q.shape[-2:]))
        return np.stack([x.T @ (x @ v) for x, v in zip(self.rows, q, strict=True)])

    def _all(self) -> np.ndarray | None:
        """All rows, over the root of N, if they are fewer than features."""
        if self.matrices is None and sum(map(len, self.rows)) < self.d:
            return np.concatenate(self.rows) / np.sqrt(self.n)
        return None

    @property
    def total(self) -> np.ndarray:
        """Mean of the node matrices: the covariance."""
        if self._total is None:
            if self.matrices is not None:
                self._total = self.matrices.mean(0)
            else:
                x = np.concatenate(self.rows)
                self._total = x.T @ x / self.n
        return self._total

    @property
    def trace(self) -> float:
        return float(np.trace(self.total)) if self.matrices is not None else float(sum((x * x).sum() for x in self.rows) / self.n)

    def mean_apply(self, q: np.ndarray) -> np.ndarray:
        x = self._all()
        return self.total @ q if x is None else x.T @ (x @ q)

    def kept(self, q: np.ndarray) -> np.ndarray:
        """Variance that each of the stacked bases keeps."""
        x = self._all()
        return np.einsum("nir,nir->n", q, self.total @ q) if x is None else ((x @ q) ** 2).sum((1, 2))

    def leading(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        """Eigenvalues in falling order and the first r eigenvectors, computed once."""
        if self._known is None or self._known[1].shape[1] < r:
            self._known = self._leading(r)
        return self._known[0], self._known[1][:, :r]

    def _leading(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        x = self._all()
        if x is None or len(x) < r:
            return leading(self.total, r)
        values, vectors = leading(x @ x.T, r)
        at = np.maximum(values[:r], 1e-300)
        return np.concatenate((values, np.zeros(self.d - len(x)))), x.T @ (vectors / np.sqrt(at))

    def column_product(self, blocks: Sequence[np.ndarray], power: np.ndarray, q: np.ndarray, rescale: str) -> np.ndarray:
        """Every holder's block of the product when the columns are split: holder i hears holder j's scores with
        the share that the power gives it."""
        share = power.T * anchor_scale(power, rescale)[:, None]
        out = np.empty_like(q)
        if self.matrices is None:
            x = self.rows[0]
            scores = np.stack([x[:, b] @ q[b] for b in blocks])
            for i, b in enumerate(blocks):
                out[b] = x[:, b].T @ np.tensordot(share[i], scores, 1)
        else:
            parts = np.stack([self.matrices[0][:, b] @ q[b] for b in blocks])
            for i, b in enumerate(blocks):
                out[b] = np.tensordot(share[i], parts[:, b], 1)
        return out / len(blocks)


PANEL = 64  # rows of a matrix that are kept from the diagonal on


def _panels(d: int) -> list[tuple[int, int]]:
    """First row and height of every panel."""
    return [(a, min(PANEL, d - a)) for a in range(0, d, PANEL)]


def _panel_size(d: int) -> int:
    return sum(w * (d - a) for a, w in _panels(d))


def _fold_rows(panels: dict[int, np.ndarray], x: np.ndarray) -> None:
    for a, own in panels.items():
        own += x[:, a : a + len(own)].T @ x[:, a:]


def _add_block(panels: dict[int, np.ndarray], low: int, block: np.ndarray, factor: float = 1.0) -> None:
    for a, own in panels.items():
        first, last = max(a, low), min(a + len(own), low + len(block))
        if first < last:
            own[first - a : last - a] += factor * block[first - low : last - low, a:]


def _pieces_of(batches: Iterable[pa.RecordBatch], d: int) -> Iterator[tuple]:
    """(node, low, block, rows, their sum or None) of every piece; one piece is in memory beside its batch's bytes."""
    for batch in batches:
        for node, low, k, n, total, body in zip(*(batch.column(c) for c in ("node", "low", "k", "n", "total", "body")), strict=True):
            yield node.as_py(), low.as_py(), np.frombuffer(body.as_buffer()).reshape(k.as_py(), d), n.as_py(), None if total.as_py() is None else np.frombuffer(total.as_py())


class CompactNodes(LocalNodes):
    """Node moments in the memory of one task, in the fewer bytes of two forms: all scaled, centred rows, or of every
    node's matrix the panels from the diagonal on. Bases are multiplied from the left, which BLAS does faster."""

    def __init__(self, n: int, d: int, rows: list[np.ndarray] | None, panels: list[dict[int, np.ndarray]] | None):
        self.n, self.d, self.rows, self.panels, self.matrices = n, d, rows, panels, None
        self._padded = self._total = self._known = None

    @classmethod
    def from_batches(cls, table: PieceTable, batches: Iterable[pa.RecordBatch]) -> CompactNodes:
        n, d, mean, factors = table.n, table.d, table.mean, table.factors
        if not table.dense and table.bytes == table.compact:
            ends = np.concatenate(([0], np.cumsum(table.rows)))
            every, at = np.empty((ends[-1], d)), ends[:-1].copy()
            for node, _, block, _, _ in _pieces_of(batches, d):
                own = every[at[node] : at[node] + len(block)]
                np.subtract(block, mean, out=own)
                own *= np.sqrt(factors[node])
                at[node] += len(block)
            if (at != ends[1:]).any():
                raise ValueError("pieces do not hold the rows counted")
            return cls(n, d, [every[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)], None)
        panels = [{a: np.zeros((w, d - a)) for a, w in _panels(d)} for _ in range(n)]
        few: list[list[np.ndarray]] = [[] for _ in range(n)]
        for node, low, block, _, _ in _pieces_of(batches, d):
            if low >= 0:
                _add_block(panels[node], low, block)
                continue
            few[node].append(block if len(block) >= PANEL else block.copy())
            if sum(map(len, few[node])) >= PANEL:
                _fold_rows(panels[node], np.concatenate(few[node]) if len(few[node]) > 1 else few[node][0])
                few[node] = []
        for node, own in enumerate(panels):
            if few[node]:
                _fold_rows(own, np.concatenate(few[node]))
                few[node] = []
            total = table.sums[node] - table.rows[node] * mean
            for a, panel in own.items():
                w = len(panel)
                panel -= np.outer(table.sums[node][a : a + w], mean[a:])
                panel -= np.outer(mean[a : a + w], total[a:])
                panel *= factors[node]
        return cls(n, d, None, panels)

    def apply(self, q: np.ndarray) -> np.ndarray:
        q = np.asarray(q)
        across = np.broadcast_to(np.swapaxes(q, -1, -2), (self.n, q.shape[-1], self.d))
        out = np.zeros(across.shape)
        for node in range(self.n):
            v, z = np.ascontiguousarray(across[node]), out[node]
            if self.panels is None:
                np.matmul(v @ self.rows[node].T, self.rows[node], out=z)
                continue
            for a, panel in self.panels[node].items():
                w = len(panel)
                z[:, a : a + w] += v[:, a:] @ panel.T
                z[:, a + w :] += v[:, a : a + w] @ panel[:, w:]
        return np.swapaxes(out, 1, 2)

    def _all(self) -> np.ndarray | None:
        return super()._all() if self.panels is None else None

    @property
    def total(self) -> np.ndarray:
        if self._total is None:
            half = {a: np.zeros((w, self.d - a)) for a, w in _panels(self.d)}
            for node in range(self.n):
                if self.panels is None:
                    _fold_rows(half, self.rows[node])
                    continue
                for a, panel in self.panels[node].items():
                    half[a] += panel
            self._total = np.empty((self.d, self.d))
            for a, panel in half.items():
                w = len(panel)
                self._total[a : a + w, a:] = panel
                self._total[a + w :, a : a + w] = panel[:, w:].T
            self._total /= self.n
        return self._total

    @property
    def trace(self) -> float:
        return float(np.trace(self.total))

    def scaled(self, by: float) -> LocalNodes:
        raise TypeError("scale the table")

    def column_product(self, blocks: Sequence[np.ndarray], power: np.ndarray, q: np.ndarray, rescale: str) -> np.ndarray:
        return as_nodes(self.total * self.n).column_product(blocks, power, q, rescale)


@dataclasses.dataclass
class StoredNodes:
    """Node moments that fit a task, in their table: a task that needs them reads the pieces itself, so that they
    pass neither the driver nor a broadcast. ``known``: their eigenvalues and leading eigenvectors."""

    table: PieceTable
    known: tuple[np.ndarray, np.ndarray]

    @property
    def n(self) -> int:
        return self.table.n

    @property
    def d(self) -> int:
        return self.table.d

    def leading(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        if self.known[1].shape[1] < r:
            raise ValueError(f"{self.known[1].shape[1]} eigenvectors are known, not {r}")
        return self.known[0], self.known[1][:, :r]

    def bare(self) -> PieceTable:
        """All but the pieces, for :meth:`CompactNodes.from_batches`."""
        return dataclasses.replace(self.table, df=None)


def as_nodes(m) -> LocalNodes:
    """Stacked matrices (or one) as node moments; node moments stay as they are."""
    if isinstance(m, np.ndarray):
        return LocalNodes(matrices=m if m.ndim == 3 else m[None])
    return m


# ---------------------------------------------------------------- distributed


class SpreadNodes:
    """Node moments that stay where they are. A product is one job of one stage: the bases are broadcast
    (their size is checked by the caller), every task multiplies its pieces, and N x d x r sums come back."""

    def __init__(self, table: PieceTable):
        self.table, self.n, self.d = table, table.n, table.d
        tasks = max(1, min(4096, int(table.bytes // TASK_BYTES) + 1))
        tasks = max(tasks, min(table.df.sparkSession.sparkContext.defaultParallelism, table.n, max(1, int(table.bytes >> 16))))
        self.df = stored(table.df.select("node", "low", "k", "body").repartition(tasks, "node", "low"), "spread")
        self._trace: float | None = None

    def _job(self, value, work, shape: tuple[int, ...]) -> Iterator[tuple[int, np.ndarray]]:
        """Arrays by key: every piece's ``work(value, node, low, block)`` yields (key, place, part), which a task
        adds up before they leave it. Small values travel with the task, larger ones as a broadcast."""
        d, sent = self.d, sum(np.asarray(v).nbytes for v in (value if isinstance(value, tuple) else (value,)))
        shared = self.df.sparkSession.sparkContext.broadcast(value) if sent > SMALL_BYTES else None
        small = value if shared is None else None

        def run(batches):
            held: dict[int, np.ndarray] = {}
            known = small if shared is None else shared.value
            for batch in batches:
                for node, low, k, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "body")), strict=True):
                    for key, at, part in work(known, node, low, np.frombuffer(body).reshape(k, d)):
                        if key not in held:
                            held[key] = np.zeros(shape)
                        held[key][at : at + len(part)] += part
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([x.tobytes() for x in held.values()], pa.binary())], ["key", "body"])

        rows = self.df.mapInArrow(run, "key int, body binary").toArrow()
        if shared is not None:
            shared.destroy()
        return ((key, np.frombuffer(body).reshape(shape)) for key, body in zip(rows["key"].to_pylist(), rows["body"].to_pylist(), strict=True))

    def apply(self, q: np.ndarray) -> np.ndarray:
        q = np.asarray(q) if np.ndim(q) == 3 else np.asarray(q)[None]
        one = len(q) == 1 or q.strides[0] == 0
        sent, d, r = np.ascontiguousarray(q[:1] if one else q), self.d, q.shape[2]

        def work(q, node, low, block):
            own = q[node if len(q) > 1 else 0]
            if low < 0:
                yield node, 0, block.T @ (block @ own)
            else:
                yield node, low, block @ own

        z = np.zeros((self.n, d, r))
        for node, part in self._job(sent, work, (d, r)):
            z[node] += part
        t = self.table
        mean, f = t.mean, t.factors
        along, own = np.tensordot(sent, mean, (1, 0)), np.einsum("nd,ndr->nr", t.sums, np.broadcast_to(sent, (self.n, d, r)))  # mean and sums along the basis
        along = np.broadcast_to(along, own.shape)
        z -= t.sums[:, :, None] * along[:, None, :] + mean[None, :, None] * (own - t.rows[:, None] * along)[:, None, :]
        return z * f[:, None, None]

    def mean_apply(self, q: np.ndarray) -> np.ndarray:
        return self.apply(q).mean(0)

    def kept(self, q: np.ndarray) -> np.ndarray:
        t, f = self.table, self.table.factors

        def work(value, node, low, block):
            q, f = value
            n, d, r = q.shape
            wide = np.ascontiguousarray(np.swapaxes(q, 0, 1)).reshape(d, n * r)
            if low < 0:
                part = ((block @ wide) ** 2).sum(0)
            else:
                part = (wide[low : low + len(block)] * (block @ wide)).sum(0)
            yield 0, 0, f[node] * part.reshape(n, r).sum(1)

        raw = np.zeros(len(q))
        for _, part in self._job((q, f), work, (len(q),)):
            raw += part
        mean, sums = t.mean, (f[:, None] * t.sums).sum(0)
        along, own = np.tensordot(q, mean, (1, 0)), np.tensordot(q, sums, (1, 0))
        return (raw - 2 * (along * own).sum(1) + (f * t.rows).sum() * (along**2).sum(1)) / self.n

    @property
    def trace(self) -> float:
        if self._trace is None:
            t, f = self.table, self.table.factors

            def work(f, node, low, block):
                yield 0, 0, f[node] * np.array([(block * block).sum() if low < 0 else np.trace(block[:, low:])])

            raw = sum(float(part[0]) for _, part in self._job(f, work, (1,)))
            mean, sums = t.mean, (f[:, None] * t.sums).sum(0)
            self._trace = float((raw - 2 * mean @ sums + (f * t.rows).sum() * mean @ mean) / self.n)
        return self._trace

    @property
    def total(self) -> np.ndarray:
        """The covariance, behind a check of its size."""
        d, t, f = self.d, self.table, self.table.factors
        if d * d * 8 > DENSE_BYTES:
            raise ValueError("the covariance exceeds the budget: give the truth as a basis")

        def run(batches):
            out = np.zeros((d, d))
            for batch in batches:
                for node, low, k, body in zip(*(batch.column(c).to_pylist() for c in ("node", "low", "k", "body")), strict=True):
                    block = np.frombuffer(body).reshape(k, d)
                    if low < 0:
                        out += f[node] * (block.T @ block)
                    else:
                        out[low : low + k] += f[node] * block
            yield from _emitted(0, d, None, out, 0, np.zeros(d))

        blocks = added(self.df.mapInArrow(run, PIECES).repartition("node", "low").sortWithinPartitions("node", "low"), d)
        rows = blocks.select("low", "body").toArrow()
        out = np.zeros((d, d))
        for low, body in zip(rows["low"].to_pylist(), rows["body"].to_pylist(), strict=True):
            block = np.frombuffer(body).reshape(-1, d)
            out[low : low + len(block)] = block
        cross = np.outer((f[:, None] * t.sums).sum(0), t.mean)
        return (out - cross - cross.T + (f * t.rows).sum() * np.outer(t.mean, t.mean)) / self.n

    def leading(self, r: int) -> tuple[np.ndarray, np.ndarray]:
        return leading(self.total, r)

    def column_product(self, blocks, power, q, rescale):
        """As in memory: the products with each holder's part of the basis, one basis wide for every holder."""
        share = power.T * anchor_scale(power, rescale)[:, None]
        r, wide = q.shape[1], np.zeros((self.d, len(blocks) * q.shape[1]))
        for j, b in enumerate(blocks):
            wide[b, j * r : (j + 1) * r] = q[b]
        parts = self.apply(wide)[0].reshape(self.d, len(blocks), r)
        out = np.empty_like(q)
        for i, b in enumerate(blocks):
            out[b] = np.einsum("j,djr->dr", share[i], parts[b])
        return out / len(blocks)


class SampleNodes:
    """One node that is the samples themselves: every product is one scan, d x r sums leave a task. The mean is d
    numbers; no d x d matrix is built."""

    n = 1

    def __init__(self, samples: DataFrame, d: int, center: str = "exact"):
        self.samples, self.d = stored(samples.select("sample_id", "features"), "columns"), d

        def run(batches):
            n, total, square = 0, np.zeros(d), np.zeros(d)
            for batch in batches:
                x = vectors_of(batch.column("features"), d) if batch.num_rows else np.zeros((0, d))
                n, total, square = n + len(x), total + x.sum(0), square + (x * x).sum(0)
            yield pa.RecordBatch.from_arrays([pa.array(range(d), pa.int32()), pa.array([n] * d, pa.int64()), pa.array(total), pa.array(square)], ["i", "n", "s", "v"])

        parts = self._features().mapInArrow(run, "i int, n long, s double, v double").groupBy("i").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("v").alias("v")).orderBy("i").toArrow()
        self.rows = int(parts["n"][0].as_py() or 0)
        if not self.rows:
            raise ValueError("no samples")
        total = np.asarray(parts["s"])
        self.mean = total / self.rows if center == "exact" else np.zeros(d)
        self.trace = float((np.asarray(parts["v"]).sum() - (self.rows * self.mean @ self.mean)) / self.rows)

    def _features(self) -> DataFrame:
        return self.samples.select(F.col("features").cast("array<double>").alias("features"))

    def _scan(self, value, work, shape: tuple[int, int]) -> np.ndarray:
        context = self.samples.sparkSession.sparkContext
        shared, d, mean = context.broadcast(value), self.d, self.mean

        def run(batches):
            out = np.zeros(shape)
            for batch in batches:
                if batch.num_rows:
                    work(shared.value, vectors_of(batch.column("features"), d) - mean, out)
            yield pa.RecordBatch.from_arrays([pa.array(range(len(out)), pa.int32()), pa.array(list(out), pa.list_(pa.float64()))], ["i", "v"])

        sums = self._features().mapInArrow(run, "i int, v array<double>").groupBy("i").agg(*[F.sum(F.element_at("v", j + 1)).alias(f"v{j}") for j in range(shape[1])]).orderBy("i").toArrow()
        shared.destroy()
        return np.column_stack([np.asarray(sums[f"v{j}"]) for j in range(shape[1])])

    def column_product(self, blocks, power, q, rescale):
        share = power.T * anchor_scale(power, rescale)[:, None]

        def work(value, x, out):
            blocks, q, share = value
            scores = np.stack([x[:, b] @ q[b] for b in blocks])
            for b, s in zip(blocks, share, strict=True):
                out[b] += x[:, b].T @ np.tensordot(s, scores, 1)

        return self._scan((blocks, q, share), work, q.shape) / (self.rows * len(blocks))

    def mean_apply(self, q: np.ndarray) -> np.ndarray:
        def work(q, x, out):
            out += x.T @ (x @ q)

        return self._scan(q, work, q.shape) / self.rows

    def kept(self, q: np.ndarray) -> np.ndarray:
        def work(q, x, out):
            out += ((x @ q) ** 2).sum((1, 2))[:, None]

        return self._scan(q, work, (len(q), 1))[:, 0] / self.rows

    def leading(self, r: int):
        raise ValueError("streamed samples build no covariance: give the truth as a basis")
