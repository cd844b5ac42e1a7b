"""LM scoring by context-tree weighting over bytes.

A text is lower-cased (A-Z only), cut into words at white space, and read as the byte string of
its words, each closed by a space, closed by a newline (the end token): token sequences and such
strings are in one-to-one correspondence, so the score is the log10 probability of the tokens.

Every byte is decomposed into eight binary decisions. For each decision and each context length
0..depth (in bytes) a node keeps two counts; its estimate is Krichevsky-Trofimov's. A node's
weighted probability is the even mixture of its own block estimate and the product of those of its
one-byte-longer contexts; the batch form needs only counts, so the order of the corpus does not
matter. A decision is scored by mixing the estimates of all depths with the posterior weights of
the nodes on the path. Mixing ends at the deepest context that training has seen.

Plan. Documents are dealt to blocks by hash and sent as compressed byte strings. A block lists its
distinct byte n-grams (context, byte) and words with their training counts; the lists are sharded
by their last three context bytes, merged, priced, and sent back to the blocks, which then score their
documents. Nothing that grows with the corpus is broadcast: only nodes of depth two or less
(at most 2**16 * 255) pass through the driver.
"""

from __future__ import annotations

import struct
from collections import Counter

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.llm.common import shuffle_partitions, stored

END = 0x0A
_TOP = 2  # nodes up to this depth are combined on the driver
_SHARD = 3  # context bytes that choose the shard
_LOG_HALF = np.log(0.5)
_LOG_PI = np.log(np.pi)


# ---------------------------------------------------------------- numeric core (numpy)


def log_gamma(x: np.ndarray) -> np.ndarray:
    """Natural log of the gamma function for x > 0 (shifted Stirling series, error < 1e-12)."""
    x = np.asarray(x, np.float64)
    low = x < 10
    shift = np.where(low, x * (x + 1) * (x + 2) * (x + 3) * (x + 4) * (x + 5) * (x + 6) * (x + 7) * (x + 8) * (x + 9), 1.0)
    y = np.where(low, x + 10, x)
    inv = 1 / y
    inv2 = inv * inv
    series = inv * (1 / 12 - inv2 * (1 / 360 - inv2 * (1 / 1260 - inv2 * (1 / 1680 - inv2 / 1188))))
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + series - np.log(shift)


def log_block(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """Log of the Krichevsky-Trofimov probability of any sequence with these counts."""
    return log_gamma(n0 + 0.5) + log_gamma(n1 + 0.5) - log_gamma(n0 + n1 + 1.0) - _LOG_PI


def n_grams(stream: np.ndarray, depth: int) -> np.ndarray:
    """Keys of all positions of ``stream`` from index ``depth`` on: the latest context byte in the
    highest place, the oldest below it, the byte itself in the lowest place."""
    byte = stream.astype(np.uint64)
    runs = {1: byte}  # runs[m][i]: m bytes ending at i + m - 1, the last one highest
    for m in (2, 4):
        half = runs[m // 2]
        runs[m] = (half[m // 2 :] << np.uint64(4 * m)) | half[: -(m // 2) or None]
    left, size = depth, 0
    context = None
    for m in (4, 2, 1):
        while left >= m:
            # the newest bytes first: this run ends `size` bytes before the context's end
            part = runs[m][depth - size - m : len(stream) - size - m]
            context = part if context is None else (context << np.uint64(8 * m)) | part
            size += m
            left -= m
    return byte[depth:] if context is None else (context << np.uint64(8)) | byte[depth:]


def counted(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys with their summed counts (each key counts once if no counts are given)."""
    if not len(keys):
        return keys.astype(np.uint64), np.zeros(0, np.int64)
    if counts is None:
        keys = np.sort(keys)
    else:
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    if counts is None:
        return keys[first], np.diff(np.append(first, len(keys))).astype(np.int64)
    return keys[first], np.add.reduceat(counts.astype(np.int64), first)


def _decisions(keys: np.ndarray, counts: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each of the 8 binary decisions: node ids (context then the bits before), counts of 0 and 1.
    ``keys``: sorted (context << 8 | byte)."""
    out = []
    for bit in range(8):
        node = keys >> np.uint64(8 - bit)
        one = ((keys >> np.uint64(7 - bit)) & np.uint64(1)).astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1]))) if len(node) else np.zeros(0, np.int64)
        if len(node):
            out.append((node[first], np.add.reduceat(counts * (1 - one), first), np.add.reduceat(counts * one, first)))
        else:
            out.append((node, counts, counts))
    return out


def _at_depth(keys: np.ndarray, counts: np.ndarray, depth: int, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts of (context of d bytes, byte) from those of (context of depth bytes, byte)."""
    if d == depth:
        return keys, counts
    return counted(((keys >> np.uint64(8 * (depth - d + 1))) << np.uint64(8)) | (keys & np.uint64(255)), counts)


def _child_sums(parents: np.ndarray, nodes: np.ndarray, logs: np.ndarray, bit: int) -> np.ndarray:
    """Sum of the children's log weighted probabilities for each sorted parent node."""
    mask = np.uint64((1 << bit) - 1)
    up = ((nodes >> np.uint64(8 + bit)) << np.uint64(bit)) | (nodes & mask)
    return np.bincount(np.searchsorted(parents, up), weights=logs, minlength=len(parents))


def grown(keys: np.ndarray, counts: np.ndarray, depth: int, low: int) -> dict[int, list]:
    """Nodes of the depths ``low``..``depth``: for each depth and decision
    ``(nodes, n0, n1, log block, log weighted)``. Keys with a zero count make no node."""
    seen = counts > 0
    keys, counts = keys[seen], counts[seen]
    tree: dict[int, list] = {}
    for d in range(depth, low - 1, -1):
        tree[d] = []
        for bit, (nodes, n0, n1) in enumerate(_decisions(*_at_depth(keys, counts, depth, d))):
            block = log_block(n0, n1)
            if d < depth:
                below = tree[d + 1][bit]
                weighted = np.logaddexp(_LOG_HALF + block, _LOG_HALF + _child_sums(nodes, below[0], below[4], bit))
            else:
                weighted = block
            tree[d].append((nodes, n0, n1, block, weighted))
    return tree


def grown_top(rows: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]) -> dict[int, list]:
    """Nodes of depth 0.._TOP from, per decision, the depth-_TOP nodes with their counts and the
    summed log weighted probability of their children."""
    tree: dict[int, list] = {d: [] for d in range(_TOP + 1)}
    for bit in range(8):
        nodes, n0, n1, below = rows[bit]
        for d in range(_TOP, -1, -1):
            block = log_block(n0, n1)
            weighted = np.logaddexp(_LOG_HALF + block, _LOG_HALF + below)
            tree[d].append((nodes, n0, n1, block, weighted))
            if d:
                mask = np.uint64((1 << bit) - 1)
                up = ((nodes >> np.uint64(8 + bit)) << np.uint64(bit)) | (nodes & mask)
                nodes, where = np.unique(up, return_inverse=True)
                n0, n1 = (np.bincount(where, weights=x, minlength=len(nodes)).astype(np.int64) for x in (n0, n1))
                below = np.bincount(where, weights=weighted, minlength=len(nodes))
    return tree


def priced(keys: np.ndarray, depth: int, tree: dict[int, list]) -> np.ndarray:
    """log10 P(byte | context) of each key, by mixing all depths of ``tree`` along its path."""
    total = np.zeros(len(keys))
    byte = keys & np.uint64(255)
    for bit in range(8):
        p = np.full(len(keys), np.nan)
        one = ((byte >> np.uint64(7 - bit)) & np.uint64(1)).astype(bool)
        for d in range(depth, -1, -1):
            nodes, n0, n1, block, weighted = tree[d][bit]
            if not len(nodes):
                continue
            own = ((keys >> np.uint64(8 * (depth - d + 1))) << np.uint64(bit)) | (byte >> np.uint64(8 - bit))
            at = np.minimum(np.searchsorted(nodes, own), len(nodes) - 1)
            found = nodes[at] == own
            estimate = (np.where(one, n1[at], n0[at]) + 0.5) / (n0[at] + n1[at] + 1.0)
            weight = np.where(np.isnan(p), 1.0, np.exp(np.minimum(0.0, _LOG_HALF + block[at] - weighted[at])))
            p = np.where(found, weight * estimate + (1 - weight) * np.nan_to_num(p), p)
        total += np.log10(np.where(np.isnan(p), 0.5, p))
    return total


# ---------------------------------------------------------------- texts


def token_bytes(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z) words of a text as UTF-8; null is empty."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def stream_of(words: list[bytes]) -> bytes:
    return b"".join([w + b" " for w in words]) + b"\n"


def _packed(streams: list[bytes]) -> bytes:
    return zstandard.compress(struct.pack(f"<{len(streams) + 1}I", len(streams), *map(len, streams)) + b"".join(streams), 3)


def _unpacked(blob: bytes) -> list[bytes]:
    raw = zstandard.decompress(blob)
    (n,) = struct.unpack_from("<I", raw)
    at, out = 4 + 4 * n, []
    for size in struct.unpack_from(f"<{n}I", raw, 4):
        out.append(raw[at : at + size])
        at += size
    return out


def _block_keys(streams: list[bytes], depth: int, chunk: int = 1 << 22):
    """Keys of many streams, in chunks; each stream starts in a context of newlines."""
    pad = bytes([END]) * depth
    part, size = [], 0
    for i, s in enumerate(streams):
        part.append(s)
        size += len(s)
        if size >= chunk or i == len(streams) - 1:
            whole = np.frombuffer(b"".join(x for s in part for x in (pad, s)), np.uint8)
            starts = np.cumsum([0] + [len(s) + depth for s in part[:-1]])
            keep = np.ones(len(whole) - depth, bool)
            if depth:
                inner = (starts[1:, None] - depth + np.arange(depth)).ravel()
                keep[inner] = False
            yield n_grams(whole, depth)[keep]
            part, size = [], 0


def _merged_keys(streams: list[bytes], depth: int) -> tuple[np.ndarray, np.ndarray]:
    parts = [counted(k) for k in _block_keys(streams, depth)]
    if len(parts) == 1:
        return parts[0]
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return counted(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))


def _delta(keys: np.ndarray) -> bytes:
    return zstandard.compress(np.diff(keys, prepend=np.uint64(0)).astype("<u8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def _undelta(blob: bytes) -> np.ndarray:
    flat = np.frombuffer(zstandard.decompress(blob), np.uint8)
    return np.cumsum(np.ascontiguousarray(flat.reshape(8, -1).T).view("<u8").ravel(), dtype=np.uint64)


def _ints(values: np.ndarray) -> bytes:
    return zstandard.compress(np.asarray(values, "<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def _unints(blob: bytes) -> np.ndarray:
    flat = np.frombuffer(zstandard.decompress(blob), np.uint8)
    return np.ascontiguousarray(flat.reshape(8, -1).T).view("<i8").ravel()


def _shard_of(keys: np.ndarray, depth: int, shards: int) -> np.ndarray:
    """Shard by the latest context bytes, mixed so that neighbours spread."""
    top = keys >> np.uint64(8 * (depth + 1 - _SHARD))
    return ((top * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(shards)


# ---------------------------------------------------------------- Spark plan


def _dealt(docs: DataFrame, blocks: int) -> DataFrame:
    """Documents as rows of (block, ids, held-out flags, compressed streams)."""
    source = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(10)) == 0, F.lit(False)).alias("held_out"),
        F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("int").alias("block"),
        "text",
    )

    def pack(batches):
        for batch in batches:
            order = np.argsort(np.asarray(batch.column("block")), kind="stable")
            held, ids = {}, {}
            streams: dict[int, list[bytes]] = {}
            block = batch.column("block").to_pylist()
            flags, names, texts = (batch.column(c) for c in ("held_out", "doc_id", "text"))
            for i in order.tolist():
                b = block[i]
                streams.setdefault(b, []).append(stream_of(token_bytes(texts[i].as_py())))
                ids.setdefault(b, []).append(names[i].as_py())
                held.setdefault(b, []).append(flags[i].as_py())
            for b, own in streams.items():
                yield pa.RecordBatch.from_pydict(
                    {"block": [b], "ids": [ids[b]], "held": [held[b]], "body": [_packed(own)]},
                    schema=pa.schema([("block", pa.int32()), ("ids", pa.list_(pa.int64())), ("held", pa.list_(pa.bool_())), ("body", pa.binary())]),
                )

    return source.mapInArrow(pack, "block int, ids array<long>, held array<boolean>, body binary")


_LISTS = "block int, shard int, keys binary, counts binary, words binary, word_counts binary"


def _listed(depth: int, shards: int):
    """A block's documents -> its distinct n-grams and words with training counts, by shard."""
    from zlib import crc32

    def run(key: tuple, group: pa.Table) -> pa.Table:
        train, other = [], []
        for flags, body in zip(group.column("held").to_pylist(), group.column("body").to_pylist(), strict=True):
            for flag, stream in zip(flags, _unpacked(body), strict=True):
                (other if flag else train).append(stream)
        keys, counts = _merged_keys(train, depth)
        more, _ = _merged_keys(other, depth)
        more = np.setdiff1d(more, keys, assume_unique=True)
        keys, counts = np.concatenate((keys, more)), np.concatenate((counts, np.zeros(len(more), np.int64)))
        order = np.argsort(keys)
        keys, counts = keys[order], counts[order]
        words = Counter()
        for stream in train:
            words.update(stream.split())
        for stream in other:
            words.update({w: 0 for w in set(stream.split()) if w not in words})
        split: list[list[bytes]] = [[] for _ in range(shards)]
        for w in words:
            split[crc32(w) % shards].append(w)
        shard = _shard_of(keys, depth, shards)
        by = np.argsort(shard, kind="stable")
        ends = np.searchsorted(shard[by], np.arange(shards + 1, dtype=np.uint64))
        block = key[0].as_py()
        rows = {n: [] for n in ("block", "shard", "keys", "counts", "words", "word_counts")}
        for s in range(shards):
            own = by[ends[s] : ends[s + 1]]
            for name, value in zip(rows, (block, s, _delta(keys[own]), _ints(counts[own]), zstandard.compress(b" ".join(split[s]), 1), _ints(np.array([words[w] for w in split[s]], np.int64))), strict=True):
                rows[name].append(value)
        return pa.table(rows, schema=pa.schema([("block", pa.int32()), ("shard", pa.int32()), ("keys", pa.binary()), ("counts", pa.binary()), ("words", pa.binary()), ("word_counts", pa.binary())]))

    return run


def _gathered(group: pa.Table) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, list[list[bytes]], dict[bytes, int]]:
    lists = [_undelta(b) for b in group.column("keys").to_pylist()]
    counts = [_unints(b) for b in group.column("counts").to_pylist()]
    keys, total = counted(np.concatenate(lists), np.concatenate(counts))
    words = [zstandard.decompress(b).split() for b in group.column("words").to_pylist()]
    sums: dict[bytes, int] = {}
    for own, n in zip(words, group.column("word_counts").to_pylist(), strict=True):
        for w, c in zip(own, _unints(n).tolist(), strict=True):
            sums[w] = sums.get(w, 0) + c
    return lists, keys, total, words, sums


def _summed(depth: int):
    """A shard's lists -> nodes of depth _TOP with counts and child sums, and word totals."""

    def run(key: tuple, group: pa.Table) -> pa.Table:
        _, keys, total, _, sums = _gathered(group)
        tree = grown(keys, total, depth, _SHARD)
        out = {n: [] for n in ("bit", "node", "n0", "n1", "below")}
        for bit in range(8):
            nodes, n0, n1, _, weighted = tree[_SHARD][bit]
            mask = np.uint64((1 << bit) - 1)
            up, where = np.unique(((nodes >> np.uint64(8 + bit)) << np.uint64(bit)) | (nodes & mask), return_inverse=True)
            out["bit"].append(np.full(len(up), bit))
            out["node"].append(up.astype(np.int64))
            out["n0"].append(np.bincount(where, weights=n0, minlength=len(up)).astype(np.int64))
            out["n1"].append(np.bincount(where, weights=n1, minlength=len(up)).astype(np.int64))
            out["below"].append(np.bincount(where, weights=weighted, minlength=len(up)))
        out["bit"].append([-1])
        out["node"].append([0])
        out["n0"].append([sum(1 for c in sums.values() if c)])
        out["n1"].append([sum(sums.values())])
        out["below"].append([0.0])
        return pa.table({k: np.concatenate(v) for k, v in out.items()}, schema=pa.schema([("bit", pa.int32()), ("node", pa.int64()), ("n0", pa.int64()), ("n1", pa.int64()), ("below", pa.float64())]))

    return run


def _answered(depth: int, top):
    """A shard's lists -> for each block the log10 probabilities of its n-grams and counts of its words."""

    def run(key: tuple, group: pa.Table) -> pa.Table:
        lists, keys, total, words, sums = _gathered(group)
        logs = priced(keys, depth, grown(keys, total, depth, _SHARD) | top.value)
        out = {n: [] for n in ("block", "keys", "logs", "words", "word_counts")}
        bodies = group.column("words").to_pylist()
        for i, block in enumerate(group.column("block").to_pylist()):
            out["block"].append(block)
            out["keys"].append(group.column("keys")[i].as_py())
            out["logs"].append(logs[np.searchsorted(keys, lists[i])].astype("<f4").tobytes())
            out["words"].append(bodies[i])
            out["word_counts"].append(_ints(np.array([sums[w] for w in words[i]], np.int64)))
        return pa.table(out, schema=pa.schema([("block", pa.int32()), ("keys", pa.binary()), ("logs", pa.binary()), ("words", pa.binary()), ("word_counts", pa.binary())]))

    return run


_SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long, bits_per_byte double"


def _scored(depth: int, n_ends: int, n_words: int, n_distinct: int):
    """A block's documents and the answers to its lists -> scores per document."""
    n_train, n_types = n_words + n_ends, n_distinct + (n_ends > 0)
    scale = float(np.log10(n_train + 0.1 * (n_types + 1)))
    end_cost = float(np.log10(n_ends + 0.1)) - scale

    def run(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        keys, logs = np.zeros(0, np.uint64), np.zeros(0)
        if right.num_rows:
            keys = np.concatenate([_undelta(b) for b in right.column("keys").to_pylist()])
            logs = np.concatenate([np.frombuffer(b, "<f4") for b in right.column("logs").to_pylist()]).astype(np.float64)
            order = np.argsort(keys)
            keys, logs = keys[order], logs[order]
        known: dict[bytes, int] = {}
        for body, n in zip(right.column("words").to_pylist(), right.column("word_counts").to_pylist(), strict=True):
            known.update(zip(zstandard.decompress(body).split(), _unints(n).tolist(), strict=True))
        cost = dict(zip(known, (np.log10(np.fromiter(known.values(), float, len(known)) + 0.1) - scale).tolist(), strict=True))
        unseen = float(np.log10(np.array([0.1]))[0] - scale)  # the cost of a count of zero and of no other
        out = {n: [] for n in _SCORE_TYPES.names}
        for ids, flags, body in zip(left.column("ids").to_pylist(), left.column("held").to_pylist(), left.column("body").to_pylist(), strict=True):
            for doc, flag, stream in zip(ids, flags, _unpacked(body), strict=True):
                own = stream.split()
                seen, times = counted(next(_block_keys([stream], depth)))
                score = float(times @ logs[np.searchsorted(keys, seen)])
                costs = list(map(cost.__getitem__, own))
                n_known = len(own) - costs.count(unseen) + (n_ends > 0)
                base = sum(costs) + end_cost
                bits = -score / float(np.log10(2)) / len(stream)
                values = (doc, flag, len(own) + 1, n_known, n_train, base, score, len(stream), bits)
                for n, v in zip(out, values, strict=True):
                    out[n].append(v)
        return pa.table(out, schema=_SCORE_TYPES)

    return run


_SCORE_TYPES = pa.schema(
    [("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64())]
    + [("base_score", pa.float64()), ("score", pa.float64()), ("n_bytes", pa.int64()), ("bits_per_byte", pa.float64())]
)


def score_documents(docs: DataFrame, depth: int = 5, block_bytes: int = 1 << 26, max_shards: int = 1024) -> DataFrame:
    """Score every document of ``docs(doc_id, text)`` with a context tree learned from those whose
    crc32(doc_id as text) mod 10 is not 0.

    Columns: doc_id, held_out, n_tokens, n_known, train_tokens, base_score (additively smoothed
    word frequencies), score (log10 probability under the tree), n_bytes, bits_per_byte (code length
    per byte). ``depth``: context bytes, 3 to 6. Null or empty texts score their end token; a null
    doc_id counts as training; repeated rows are scored (and learned) once each; no documents give
    no rows; other columns are ignored.
    """
    if not _SHARD <= depth <= 6:
        raise ValueError("depth must be 3 to 6")
    spark = docs.sparkSession
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(10)) == 0, F.lit(False))
    n_ends, size = docs.agg(F.count(F.when(~held, 1)), F.sum(F.octet_length("text"))).first()
    blocks = max(shuffle_partitions(spark), -(-(size or 0) // block_bytes))
    shards = min(shuffle_partitions(spark), max_shards)
    lists = stored(_dealt(docs, blocks).groupBy("block").applyInArrow(_listed(depth, shards), _LISTS), "lists")
    nodes = lists.groupBy("shard").applyInArrow(_summed(depth), "bit int, node long, n0 long, n1 long, below double")
    # Nodes of depth two: at most 2**16 * 255 whatever the corpus.
    upper = nodes.groupBy("bit", "node").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("below").alias("below")).toPandas()
    totals = upper[upper.bit < 0]
    n_distinct, n_words = (int(totals[c].sum()) for c in ("n0", "n1"))
    rows = {}
    for bit in range(8):
        own = upper[upper.bit == bit].sort_values("node")
        rows[bit] = (own.node.to_numpy().astype(np.uint64), own.n0.to_numpy(), own.n1.to_numpy(), own.below.to_numpy())
    top = spark.sparkContext.broadcast(grown_top(rows))
    answers = lists.groupBy("shard").applyInArrow(_answered(depth, top), "block int, keys binary, logs binary, words binary, word_counts binary")
    return (
        _dealt(docs, blocks)
        .groupBy("block")
        .cogroup(answers.groupBy("block"))
        .applyInArrow(
            _scored(depth, n_ends, n_words, n_distinct),
            "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long, bits_per_byte double",
        )
    )
