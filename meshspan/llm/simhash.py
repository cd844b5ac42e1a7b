"""SimHash near-dedup with multi-index hashing.

A text's fingerprint has a bit set where over half of its shingles' 64-bit hashes have it set.
Distinct fingerprints are linked at ``RADIUS`` or fewer differing bits: the 64 bits are cut into
three segments; two linked fingerprints differ by at most one bit in the first segment, or by at
most one in the second, or agree in the third (differing by 2 + 2 + 1 would exceed four). So each
fingerprint is entered in a table per segment under its own segment value, and probes the small
balls of radius one around it; only flips of a 0 to a 1 are probed, since of two values one bit
apart one is the other's flip. What meets under a table key is verified over all 64 bits. A key's
matches are returned as a spanning forest, never as all pairs; a key that very many fingerprints
share is searched by a finer index of the same kind.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.llm.common import connected_components, shuffle_partitions, stored

RADIUS = 4
#: (lowest bit, width, ball radius) of the segments.
SEGMENTS = ((0, 21, 1), (21, 21, 1), (42, 22, 0))
_SEED = 42
_DENSE = 256  # runs up to this length are compared pair by pair, in numpy


def fingerprint(text: str | None, shingle: int = 4) -> int:
    """Fingerprint of one text; null and wordless texts have fingerprint zero."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) <= shingle:
        grams = [b" ".join(words)]
    else:
        grams = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(g, _SEED) for g in grams), np.uint64)
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = np.ascontiguousarray(hashes[at : at + (1 << 16)]).view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(0, dtype=np.int64)
    value = 0
    for bit in np.flatnonzero(ones * 2 > len(hashes)).tolist():
        value |= 1 << bit
    return value


def with_fingerprints(docs: DataFrame, shingle: int = 4, keys: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, fp) of every row, and its columns ``keys`` (longs); fp is the fingerprint's 64 bits as a signed long."""

    def run(batches):
        for batch in batches:
            texts = batch.column("text")
            values = np.array([fingerprint(texts[i].as_py(), shingle) for i in range(batch.num_rows)], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(values.view(np.int64)), *(batch.column(k) for k in keys)], ["doc_id", "fp", *keys])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *keys).mapInArrow(run, ", ".join(f"{c} long" for c in ("doc_id", "fp", *keys)))


# ---------------------------------------------------------------- links under one key


def forest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest reachable index of each of ``n`` items, given linked index pairs (a, b)."""
    root = np.arange(n)
    while len(a):
        low, high = np.minimum(root[a], root[b]), np.maximum(root[a], root[b])
        moved = low != high
        a, b, low, high = a[moved], b[moved], low[moved], high[moved]
        if not len(a):
            break
        np.minimum.at(root, high, low)
        while True:
            jumped = root[root]
            if np.array_equal(jumped, root):
                break
            root = jumped
    return root


def _close(x: np.ndarray, y: np.ndarray, radius: int) -> np.ndarray:
    return np.bitwise_count(x ^ y) <= radius


def linked_run(values: np.ndarray, radius: int = RADIUS, dense: int = _DENSE) -> np.ndarray:
    """Roots (smallest index reachable by links) of distinct fingerprints that share a key.

    Long runs are indexed by ``radius + 1`` segments of equal width: two linked values agree in one
    of them whole. What still shares a segment value in numbers is compared in blocks.
    """
    n = len(values)
    if n <= dense:
        close = np.triu(_close(values[:, None], values[None, :], radius), 1)
        return forest(*np.nonzero(close), n)
    root = np.arange(n)
    edges = np.linspace(0, 64, radius + 2).astype(int)
    for low, high in zip(edges[:-1], edges[1:], strict=True):
        part = (values >> np.uint64(low)) & np.uint64((1 << int(high - low)) - 1)
        order = np.argsort(part, kind="stable")
        starts = np.flatnonzero(np.concatenate(([True], np.diff(part[order]) != 0)))
        for s, e in zip(starts, np.append(starts[1:], n), strict=True):
            own = order[s:e]
            if len(own) == 1:
                continue
            pairs = []
            for at in range(0, len(own), dense):
                head = own[at : at + dense]
                # an item already joined to this block's items gives no new edge; verify the others
                i, j = np.nonzero(_close(values[head][:, None], values[own][None, at:], radius))
                apart = root[head[i]] != root[own[at + j]]
                if apart.any():
                    pairs.append((head[i[apart]], own[at + j[apart]]))
            if pairs:
                a, b = (np.concatenate(x) for x in zip(*pairs, strict=True))
                merged = forest(root[a], root[b], n)
                root = merged[root]
    return root


def _runs(keys: np.ndarray, values: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Forest edges (value, root's value) within each run of equal keys; keys are sorted."""
    starts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    sizes = np.diff(np.append(starts, len(keys)))
    out_a, out_b = [], []
    small = sizes <= 8
    length = np.repeat(np.where(small, sizes, 0), sizes)
    place = np.arange(len(keys)) - np.repeat(starts, sizes)
    for step in range(1, 8):
        at = np.flatnonzero(place + step < length)
        if not len(at):
            break
        hit = at[_close(values[at], values[at + step], radius)]
        out_a.append(values[hit])
        out_b.append(values[hit + step])
    for s, size in zip(starts[~small].tolist(), sizes[~small].tolist(), strict=True):
        own = np.unique(values[s : s + size])
        root = linked_run(own, radius)
        moved = np.flatnonzero(root != np.arange(len(own)))
        out_a.append(own[moved])
        out_b.append(own[root[moved]])
    if not out_a:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    a, b = np.concatenate(out_a), np.concatenate(out_b)
    differ = a != b
    return a[differ], b[differ]


def _entries(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Table entries and probes: key (segment number, segment value) and fingerprint."""
    keys, owners = [], []
    for number, (low, width, radius) in enumerate(SEGMENTS):
        part = (fps >> np.uint64(low)) & np.uint64((1 << width) - 1)
        tag = np.uint64(number << 32)
        keys.append(part | tag)
        owners.append(fps)
        for bit in range(width if radius else 0):
            flip = np.uint64(1 << bit)
            zero = (part & flip) == 0
            keys.append(part[zero] | flip | tag)
            owners.append(fps[zero])
    return np.concatenate(keys), np.concatenate(owners)


def fingerprint_links(fps: DataFrame) -> DataFrame:
    """Links (src, dst) that join all linked distinct fingerprints of ``fps(fp)``: a spanning forest
    under each table key, all distances verified."""
    types = pa.schema([("key", pa.int64()), ("fp", pa.int64())])

    def enter(batches):
        for batch in batches:
            keys, owners = _entries(np.asarray(batch.column("fp")).view(np.uint64))
            for at in range(0, len(keys), 1 << 17):
                part = slice(at, at + (1 << 17))
                yield pa.RecordBatch.from_arrays([pa.array(keys[part].astype(np.int64)), pa.array(owners[part].view(np.int64))], schema=types)

    def meet(batches):
        kept_keys, kept_values = [], []

        def flush(keys, values):
            a, b = _runs(keys, values, RADIUS)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(x.view(np.int64)) for x in (a, b)], ["src", "dst"])

        for batch in batches:
            keys, values = np.asarray(batch.column("key")), np.asarray(batch.column("fp")).view(np.uint64)
            if not len(keys):
                continue
            last = np.searchsorted(keys, keys[-1])  # the last key may go on in the next batch
            if last:
                yield from flush(np.concatenate([*kept_keys, keys[:last]]), np.concatenate([*kept_values, values[:last]]))
                kept_keys, kept_values = [], []
            elif kept_keys and kept_keys[-1][-1] != keys[0]:
                yield from flush(np.concatenate(kept_keys), np.concatenate(kept_values))
                kept_keys, kept_values = [], []
            kept_keys.append(keys[last:])
            kept_values.append(values[last:])
        if kept_keys:
            yield from flush(np.concatenate(kept_keys), np.concatenate(kept_values))

    entries = fps.select("fp").mapInArrow(enter, "key long, fp long")
    n = shuffle_partitions(fps.sparkSession)
    return entries.repartition(n, "key").sortWithinPartitions("key").mapInArrow(meet, "src long, dst long").distinct()


def near_duplicate_groups(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """Groups of near-copies among ``docs(doc_id, text)``: one row per input row with doc_id,
    fingerprint (16 hexadecimal digits) and component_id, the smallest doc_id reachable by links.

    Equal fingerprints are one class, so copies are never paired. Null and empty texts have
    fingerprint zero and link like any other; repeated rows come back as often as they came in; a
    null doc_id belongs to a group but names it only if all its ids are null; an empty table gives
    no rows; other columns are ignored.
    """
    prints = stored(with_fingerprints(docs, shingle), "prints")
    classes = stored(prints.groupBy("fp").agg(F.min("doc_id").alias("low")), "classes")
    parts = connected_components(fingerprint_links(classes))
    joined = classes.join(parts, classes.fp == parts.node, "left").select("fp", "low", F.coalesce("component", "fp").alias("part"))
    joined = stored(joined, "parts")
    named = stored(joined.groupBy("part").agg(F.min("low").alias("component_id")), "named")
    groups = stored(joined.join(named, "part").select("fp", "component_id"), "groups")
    return prints.join(groups, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def fingerprint_groups(docs: DataFrame) -> DataFrame:
    """(doc_id, k1, k2, component) of every row, as :func:`similar_groups` gives them, by fingerprints that link."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *row_key(), "text")
    prints = stored(with_fingerprints(keyed, keys=("k1", "k2")), "prints")
    parts = connected_components(fingerprint_links(prints.select("fp").distinct()))
    return prints.join(parts, prints.fp == parts.node, "left").select("doc_id", "k1", "k2", F.coalesce("component", "fp").alias("component"))


# ---------------------------------------------------------------- by similarity of shingle sets

WIDE_WORDS = 8  # 64-bit words of a wide fingerprint
WIDE_SEGMENTS = 20  # 16-bit segments that are indexed, balls of radius one
_ENTRY = np.dtype([("value", "<u2"), ("guest", "?"), ("id", "<i8"), ("fp", "<u8", (WIDE_WORDS,))])


def shingle_set(text: str | None, shingle: int = 5) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles (all words, if fewer); empty without words."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    grams = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False)) if len(words) > shingle else [b" ".join(words)]
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(g, _SEED) for g in grams), np.uint64))


def wide_fingerprint(hashes: np.ndarray) -> np.ndarray:
    """512-bit fingerprint of a set of shingles; zero of none."""
    if not len(hashes):
        return np.zeros(WIDE_WORDS, np.uint64)
    ones = np.zeros(64 * WIDE_WORDS, np.int64)
    for at in range(0, len(hashes), 1 << 14):
        part = hashes[at : at + (1 << 14), None] + np.arange(1, WIDE_WORDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            part = (part ^ (part >> np.uint64(shift))) * np.uint64(factor)
        part ^= part >> np.uint64(31)
        ones += np.unpackbits(part.view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")


def wide_radius(similarity: float) -> int:
    """Differing bits that sets of this similarity have, and four standard deviations more: two equally
    large sets of Jaccard similarity J lie at the angle acos(2 J / (1 + J)), and each bit differs with the
    probability of that angle over pi."""
    bits, p = 64 * WIDE_WORDS, np.arccos(2 * similarity / (1 + similarity)) / np.pi
    return round(bits * p + 4 * np.sqrt(bits * p * (1 - p)))


def _met(owners: np.ndarray, asked: np.ndarray, chunk: int = 1 << 20):
    """Index pairs (asked, owner) of equal values; ``owners`` is sorted. In bounded chunks."""
    left = np.searchsorted(owners, asked)
    counts = np.searchsorted(owners, asked, "right") - left
    ends = np.cumsum(counts)
    start = 0
    while start < len(asked):
        stop = max(start + 1, int(np.searchsorted(ends, (ends[start - 1] if start else 0) + chunk, "right")))
        own = counts[start:stop]
        i = np.repeat(np.arange(start, stop), own)
        j = np.arange(len(i)) - np.repeat(np.cumsum(own) - own, own) + np.repeat(left[start:stop], own)
        if len(i):
            yield i, j
        start = stop


def linked_part(entries: np.ndarray, radius: int, low_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest (id, root id) of what meets within one segment's values of a shared head: equal values,
    values one low bit apart, and guests, whose differing bit lies in the head. All bits are verified."""
    entries = entries[np.lexsort((entries["id"], entries["value"], entries["guest"]))]
    values, fps, n = entries["value"], entries["fp"], len(entries)
    own = int((~entries["guest"]).sum())
    root = np.arange(n)
    tries = [(np.arange(own), values[:own]), (np.arange(own, n), values[own:])]
    for bit in range(low_bits):
        zero = np.flatnonzero((values[:own] >> bit) & 1 == 0)
        tries.append((zero, values[zero] | np.uint16(1 << bit)))
    for who, asked in tries:
        for i, j in _met(values[:own], asked):
            i = who[i]
            apart = (root[i] != root[j]) & (i != j)
            i, j = i[apart], j[apart]
            if len(i):
                close = np.bitwise_count(fps[i] ^ fps[j]).sum(1, dtype=np.int64) <= radius
                if close.any():
                    root = forest(root[i[close]], root[j[close]], n)[root]
    moved = np.flatnonzero(root != np.arange(n))
    return entries["id"][moved], entries["id"][root[moved]]


FEW = 40  # shingles up to which sets are met by their shingles, not by fingerprints
_CHUNK = 2048  # sets of a task, beyond which a group is verified by pairs of its chunks
_FILTER_BITS = 1 << 26  # of the map of classes to verify


def verified_links(sets: list[np.ndarray], fps: np.ndarray, similarity: float, radius: int, apart: np.ndarray | None = None) -> np.ndarray:
    """Roots (smallest index reachable) of sets whose Jaccard similarity is at least ``similarity``. Pairs beyond the
    fingerprint radius (unless a set has few shingles) or of too different sizes are passed over, and pairs that
    are joined already; all others are compared shingle by shingle. ``apart``: side of each set, if only pairs of
    different sides are due."""
    n, root = len(sets), np.arange(len(sets))
    sizes = np.array([len(x) for x in sets])
    few = sizes <= FEW

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for i in range(n):
        low, high = np.minimum(sizes[i], sizes[:i]), np.maximum(sizes[i], sizes[:i])
        due = low >= similarity * high - 1e-9
        if apart is not None:
            due &= apart[:i] != apart[i]
        j = np.flatnonzero(due)
        if len(j):
            near = (np.bitwise_count(fps[j] ^ fps[i]).sum(1, dtype=np.int64) <= radius) | (few[j] & few[i])
            j = j[near]
        for k in j.tolist():
            a, b = find(i), find(k)
            if a == b:
                continue
            shared = len(np.intersect1d(sets[i], sets[k], assume_unique=True))
            if shared >= similarity * (sizes[i] + sizes[k] - shared) - 1e-9:
                root[max(a, b)] = min(a, b)
    return np.array([find(i) for i in range(n)], int)


def _marked(classes: DataFrame) -> np.ndarray:
    """A map of bits of the classes' ids: of fixed size whatever their number; a class that is not in the table may
    be marked, one that is in it always is."""

    def marks(batches):
        out = np.zeros(_FILTER_BITS // 8, np.uint8)
        for batch in batches:
            at = np.asarray(batch.column("class")).view(np.uint64) % np.uint64(_FILTER_BITS)
            np.bitwise_or.at(out, (at >> np.uint64(3)).astype(np.int64), np.left_shift(np.uint8(1), (at & np.uint64(7)).astype(np.uint8)))
        words = out.view("<u8")
        some = np.flatnonzero(words)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(words[some].view(np.int64))], ["at", "bits"])

    rows = classes.select("class").mapInArrow(marks, "at long, bits long").groupBy("at").agg(F.bit_or("bits").alias("bits")).toArrow()
    out = np.zeros(_FILTER_BITS // 64, "<u8")
    out[np.asarray(rows["at"])] = np.asarray(rows["bits"]).view(np.uint64)
    return out


def similar_groups(docs: DataFrame, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """Groups of documents whose sets of ``shingle``-word shingles have a Jaccard similarity of at least
    ``similarity``, chains included: (doc_id, k1, k2, component) of every row, k1 and k2 being a key of the row's
    doc_id and text.

    Wide fingerprints find the candidates: balls of radius one in 20 segments of 16 bits, the segment tables cut by
    the head of their value, so that flips of the other bits need no message, and all 512 bits within four
    deviations of what such pairs differ by. Sets of few shingles, which fingerprints tell poorly, meet by the
    shingles of their prefix instead: two sets of such similarity share one. What meets is a candidate group; within
    it, shingle sets decide every link. Groups beyond a task's size are verified by pairs of their chunks.

    Equal sets are one class; null and wordless texts form one group; repeated rows are copies; an empty table
    gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    radius = wide_radius(similarity)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *row_key(), "text")

    def hashed(batches):
        for batch in batches:
            texts = batch.column("text")
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = [shingle_set(texts[i].as_py(), shingle) for i in range(at, at + part.num_rows)]
                fps = [wide_fingerprint(x).tobytes() for x in sets]
                ids = [xxhash.xxh64_intdigest(x.tobytes(), _SEED) for x in sets]
                heads = [x[: len(x) - int(np.ceil(similarity * len(x) - 1e-9)) + 1].tobytes() if len(x) <= FEW else None for x in sets]
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c) for c in ("doc_id", "k1", "k2")), pa.array(np.array(ids, np.uint64).view(np.int64)), pa.array(fps, pa.binary()), pa.array(heads, pa.binary())],
                    ["doc_id", "k1", "k2", "class", "fp", "prefix"],
                )

    prints = stored(keyed.mapInArrow(hashed, "doc_id long, k1 long, k2 long, class long, fp binary, prefix binary"), "prints")
    classes = stored(prints.groupBy("class", "fp").agg(F.first("prefix").alias("prefix")), "classes")
    head = min(12, max(3, (shuffle_partitions(spark) // WIDE_SEGMENTS + 1).bit_length(), (classes.count() // 50_000).bit_length()))
    low_bits = 16 - head

    def enter(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            fps = np.frombuffer(b"".join(batch.column("fp").to_pylist()), "<u8").reshape(-1, WIDE_WORDS)
            ids, segments = np.asarray(batch.column("class")), np.ascontiguousarray(fps).view("<u2")
            for k in range(WIDE_SEGMENTS):
                value = segments[:, k]
                rows, parts = [], []
                for bit in [None, *range(low_bits, 16)]:
                    who = np.arange(len(ids)) if bit is None else np.flatnonzero((value >> bit) & 1 == 0)
                    entry = np.zeros(len(who), _ENTRY)
                    entry["value"] = value[who] if bit is None else value[who] | np.uint16(1 << bit)
                    entry["guest"], entry["id"], entry["fp"] = bit is not None, ids[who], fps[who]
                    rows.append(entry)
                    parts.append((k << head) | (entry["value"] >> low_bits).astype(np.int64))
                entry, part = np.concatenate(rows), np.concatenate(parts)
                order = np.argsort(part, kind="stable")
                starts = np.flatnonzero(np.concatenate(([True], np.diff(part[order]) != 0)))
                for s, e in zip(starts, np.append(starts[1:], len(order)), strict=True):
                    yield pa.RecordBatch.from_pydict({"part": [int(part[order[s]])], "body": [entry[order[s:e]].tobytes()]}, schema=pa.schema([("part", pa.int64()), ("body", pa.binary())]))

    def meet(key: tuple, group: pa.Table) -> pa.Table:
        entries = np.concatenate([np.frombuffer(b, _ENTRY) for b in group["body"].to_pylist()])
        a, b = linked_part(entries, radius, low_bits)
        return pa.table({"src": pa.array(a, pa.int64()), "dst": pa.array(b, pa.int64())})

    def prefixes(batches):
        for batch in batches:
            for c, p in zip(batch.column("class").to_pylist(), batch.column("prefix").to_pylist(), strict=True):
                heads = np.frombuffer(p, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(heads), c), pa.int64()), pa.array(heads, pa.int64())], ["class", "key"])

    # candidate groups: what fingerprints join, and what shares a shingle of a short prefix
    loose = connected_components(classes.select("class", "fp").mapInArrow(enter, "part long, body binary").groupBy("part").applyInArrow(meet, "src long, dst long").distinct())
    met = classes.where("prefix is not null").select("class", "prefix").mapInArrow(prefixes, "class long, key long")
    several = met.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    groups = stored(loose.select(F.col("node").alias("class"), F.col("component").alias("key"), F.lit(0).alias("way")).union(met.join(several, "key").select("class", "key", F.lit(1).alias("way"))), "candidates")
    chunks = groups.groupBy("way", "key").agg(F.ceil(F.count("*") / (_CHUNK // 2)).cast("int").alias("chunks")).where("chunks > 2")
    wanted = spark.sparkContext.broadcast(_marked(groups))

    def sets_of(batches):
        for batch in batches:
            marks = wanted.value
            texts = batch.column("text")
            ids, fps, bodies = [], [], []
            for i in range(batch.num_rows):
                x = shingle_set(texts[i].as_py(), shingle)
                c = xxhash.xxh64_intdigest(x.tobytes(), _SEED)
                at = c % _FILTER_BITS
                if (int(marks[at >> 6]) >> (at & 63)) & 1:
                    ids.append(c)
                    fps.append(wide_fingerprint(x).tobytes())
                    bodies.append(x.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(np.array(ids, np.uint64).view(np.int64)), pa.array(fps, pa.binary()), pa.array(bodies, pa.binary())], ["class", "fp", "body"])

    sets = stored(docs.select("text").mapInArrow(sets_of, "class long, fp binary, body binary").groupBy("class").agg(F.first("fp").alias("fp"), F.first("body").alias("body")), "sets")
    placed = groups.join(chunks, ["way", "key"], "left").withColumn("chunks", F.coalesce("chunks", F.lit(1))).withColumn("chunk", F.pmod(F.xxhash64("class"), F.col("chunks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    placed = placed.select("way", "key", "class", "chunk", F.least("chunk", "other").alias("low"), F.greatest("chunk", "other").alias("high"))

    def verify(key: tuple, group: pa.Table) -> pa.Table:
        group = group.sort_by("class")
        ids, chunk = np.asarray(group["class"]), np.asarray(group["chunk"])
        sets = [np.frombuffer(b, np.uint64) for b in group["body"].to_pylist()]
        fps = np.frombuffer(b"".join(group["fp"].to_pylist()), "<u8").reshape(-1, WIDE_WORDS)
        root = verified_links(sets, fps, similarity, radius, chunk if key[2].as_py() != key[3].as_py() else None)
        moved = np.flatnonzero(root != np.arange(len(ids)))
        return pa.table({"src": pa.array(ids[moved], pa.int64()), "dst": pa.array(ids[root[moved]], pa.int64())})

    links = placed.join(sets, "class").groupBy("way", "key", "low", "high").applyInArrow(verify, "src long, dst long")
    parts = stored(connected_components(links.distinct()), "components")
    return prints.select("doc_id", "k1", "k2", "class").join(parts.withColumnRenamed("node", "class"), "class", "left").select("doc_id", "k1", "k2", F.coalesce("component", "class").alias("component"))


def row_key() -> list:
    """Two hashes of a row's doc_id and text."""
    return [F.xxhash64("text", F.col("doc_id").cast("long")).alias("k1"), F.xxhash64(F.lit(_SEED), F.col("doc_id").cast("long"), F.lit("|"), F.reverse("text")).alias("k2")]


def deduplicated(docs: DataFrame, similarity: float | None = 0.8) -> DataFrame:
    """The documents without near-copies: of each group of :func:`similar_groups` (without a similarity: of fingerprints
    that link, as in :func:`near_duplicate_groups`) the row with the smallest doc_id stays (rows without one come last;
    one of rows that repeat). All columns of ``docs`` are kept; ``_k1`` and
    ``_k2`` may not be among them."""
    whole = stored(docs, "docs")
    groups = stored(fingerprint_groups(whole) if similarity is None else similar_groups(whole, similarity), "groups")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "k1", "k2")).alias("head")
    heads = groups.groupBy("component").agg(first, F.count("*").alias("n")).where("n > 1").select("component", "head")
    members = groups.join(heads, "component")
    gone = members.where((F.col("k1") != F.col("head.k1")) | (F.col("k2") != F.col("head.k2"))).select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).distinct()
    repeated = stored(members.where((F.col("k1") == F.col("head.k1")) & (F.col("k2") == F.col("head.k2"))).groupBy(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).count().where("count > 1").select("_k1", "_k2"), "repeated")
    k1, k2 = row_key()
    left = whole.withColumns({"_k1": k1, "_k2": k2}).join(gone, ["_k1", "_k2"], "left_anti")
    if repeated.limit(1).count():
        once = left.join(repeated, ["_k1", "_k2"], "left_semi").dropDuplicates(["_k1", "_k2"])
        left = left.join(repeated, ["_k1", "_k2"], "left_anti").unionByName(once)
    return left.select(*docs.columns)
