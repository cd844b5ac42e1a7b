"""Hierarchical multi-length packing of tokenised documents into training sequences.

One pass, no shuffle. Each task streams its documents: a document's ids are cut into whole long
windows plus a remainder, and the remainder is routed to the smallest context tier that holds it.
Tiers are packed longest piece first into open windows of their own size; a gap that no waiting
piece of its own tier fits is filled from the shorter tiers, longest first, and at last by cutting a
piece, so that every window but the task's last ones is exactly full. What is left at the end of a
task is cut to powers of two, which need no padding. Windows of a tier are numbered into step groups
of equal token count. Waiting pieces are held to a token budget, so memory does not grow with the
task; ids are unique across tasks because they start with the task's number.
"""

from __future__ import annotations

import array
import bisect
import zlib

import numpy as np
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LONG = 4096
TIERS = (512, 1024, 2048, LONG)
END_ID = 2
_END = np.array([END_ID], "<u2").tobytes()
_WORDS, _RUNS_KEPT = 400_000, 700_000  # words and runs whose ids a worker remembers
_KNOWN: dict[str, tuple[_Words, dict[str, bytes]]] = {}
_PLAIN = regex.compile(r"[\x21-\x7E\u00C0-\u012F\u0131-\u024F]+")
# Fixed value: the runs on which the tokenizer file's pre-tokenizer works.
_RUNS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")


def _byte_signs() -> dict[int, int]:
    """The characters by which byte-level tokenizers write the 256 bytes: printable Latin-1 stands
    for itself, the other bytes take U+0100 onwards in order."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    other = [b for b in range(256) if b not in printable]
    return {b: 0x100 + i for i, b in enumerate(other)}


_BYTE_SIGNS = _byte_signs()
_PAIRS = [i.to_bytes(2, "little") for i in range(1 << 16)]

PIECE = pa.schema(
    [("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64())]
    + [("sequence_id", pa.int64()), ("offset", pa.int64()), ("tier", pa.int32()), ("step_group", pa.int64())]
)
PIECE_DDL = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, step_group long"


class _Words(dict):
    """Ids by word; a word that is not known is asked for once."""

    def __missing__(self, word: bytes) -> bytes:
        known = self[word] = self.ask(word)
        return known


class WordTokenizer:
    """Ids of whole texts by a public byte-level BPE tokenizer file whose pieces never cross white space.

    Texts are cut at ASCII white space, and each distinct word, then each distinct run of letters or
    symbols in it, is merged once while a worker remembers it; that equals encoding the whole text,
    because the tokenizer lower-cases, drops white space and merges such runs one by one. Words with
    characters outside ASCII and extended Latin, or with the string of a special token, go to the library whole.
    What a worker remembers is bounded.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        special = [t.content.encode() for t in self.library.get_added_tokens_decoder().values()]
        self.special = regex.compile(b"|".join(map(regex.escape, special)) if special else rb"(?!)")
        self.model = self.library.model
        if self.library.get_vocab_size() >= 1 << 16:
            raise ValueError("ids must fit 16 bits")
        self.words, self.runs = _KNOWN.setdefault(path, (_Words(), {}))
        self.words.ask = self._word

    def _run(self, run: str) -> bytes:
        known = self.runs.get(run)
        if known is None:
            signs = run if run.isascii() else run.encode().decode("latin-1").translate(_BYTE_SIGNS)
            known = self.runs[run] = b"".join([_PAIRS[t.id] for t in self.model.tokenize(signs)])
        return known

    def _word(self, word: bytes) -> bytes:
        if word.isalpha():
            return self._run(word.lower().decode())
        if word[:-1].isalpha() and word[-1] < 128:
            if not word[-1:].isdigit():
                text = word.lower().decode()
                return self._run(text[:-1]) + self._run(text[-1])
        text = word.decode("utf-8")
        if not _PLAIN.fullmatch(text) or self.special.search(word):
            ids = self.library.encode(text, add_special_tokens=False).ids
            return array.array("H", ids).tobytes()
        text = text.lower()
        if text.isalpha():
            return self._run(text)
        known, run = self.runs.get, self._run
        return b"".join([known(r) or run(r) for r in _RUNS.findall(text)])

    def __call__(self, texts: list[str]) -> list[np.ndarray]:
        split = [t.encode("utf-8").split() for t in texts]
        words = self.words
        if len(words) > _WORDS:
            words.clear()
        if len(self.runs) > _RUNS_KEPT:
            self.runs.clear()
        get = words.__getitem__
        return [np.frombuffer(b"".join(map(get, own)) + _END, "<u2").astype("<u4") for own in split]


class Packer:
    """Packs pieces into windows; ``rows`` collects the placed pieces."""

    def __init__(self, base: int, tiers: tuple[int, ...] = TIERS, step_tokens: int = 64 * LONG, held_tokens: int = 1 << 20):
        self.tiers, self.step_tokens, self.held_tokens = tiers, step_tokens, held_tokens
        self.base = base
        self.next_id = 0
        self.made = dict.fromkeys(tiers, 0)
        self.waiting: dict[int, list] = {t: [] for t in tiers}  # (length, arrival, doc, start, ids, total)
        self.held = 0
        self.arrived = 0
        self.rows: dict[str, list] = {n: [] for n in PIECE.names}

    def add(self, doc, ids: np.ndarray) -> None:
        total, at = len(ids), 0
        while total - at >= self.tiers[-1]:
            self._emit([(doc, at, ids[at : at + self.tiers[-1]], total)], self.tiers[-1])
            at += self.tiers[-1]
        if at < total:
            self._wait(doc, at, ids[at:], total)
        if self.held > self.held_tokens:
            self._pack(self.held_tokens // 2)

    def _wait(self, doc, start, ids, total) -> None:
        tier = self.tiers[bisect.bisect_left(self.tiers, len(ids))]
        bisect.insort(self.waiting[tier], (len(ids), -self.arrived, doc, start, ids, total), key=lambda x: x[:2])
        self.arrived += 1
        self.held += len(ids)

    def _take(self, limit: int, most: int):
        """The longest waiting piece of at most ``most`` ids from the tiers up to ``limit``."""
        for tier in reversed([t for t in self.tiers if t <= limit]):
            pool = self.waiting[tier]
            at = bisect.bisect_right(pool, most, key=lambda x: x[0]) - 1
            if at >= 0:
                piece = pool.pop(at)
                self.held -= piece[0]
                return piece
        return None

    def _pack(self, down_to: int) -> None:
        """Fill whole windows, the tier with most waiting tokens first, until few ids wait."""
        while self.held > down_to:
            tier = max(self.tiers, key=lambda t: sum(x[0] for x in self.waiting[t][-64:]))
            if self.held < tier:
                tier = max((t for t in self.tiers if t <= self.held), default=0)
            if not tier:
                return
            self._window(tier)

    def _window(self, tier: int) -> None:
        room, placed = tier, []
        while room:
            piece = self._take(tier, room)
            if piece is None:  # nothing fits whole: cut the shortest waiting piece that is longer
                source = next(t for t in self.tiers if self.waiting[t])
                length, _, doc, start, ids, total = self.waiting[source].pop(0)
                self.held -= length
                placed.append((doc, start, ids[:room], total))
                self._wait(doc, start + room, ids[room:], total)
                break
            placed.append(piece[2:6])
            room -= piece[0]
        self._emit(placed, tier)

    def finish(self) -> None:
        """Pack all that waits: whole long windows, then powers of two."""
        self._pack(self.tiers[-1] - 1)
        size = self.tiers[-1]
        while self.held:
            while size > self.held:
                size //= 2
            self._window_of(size)

    def _window_of(self, size: int) -> None:
        room, placed = size, []
        while room:
            source = next(t for t in reversed(self.tiers) if self.waiting[t])
            length, _, doc, start, ids, total = self.waiting[source].pop()
            self.held -= length
            if length > room:
                self._wait(doc, start + room, ids[room:], total)
                ids = ids[:room]
            placed.append((doc, start, ids, total))
            room -= len(ids)
        self._emit(placed, size)

    def _emit(self, placed: list, tier: int) -> None:
        sequence, offset = self.base + self.next_id, 0
        self.next_id += 1
        nth = self.made.get(tier, 0)
        self.made[tier] = nth + 1
        group = self.base + (nth // max(1, self.step_tokens // tier)) * 64 + tier.bit_length()
        for doc, start, ids, total in placed:
            values = (doc, start, len(ids), zlib.crc32(ids.tobytes()), total, sequence, offset, tier, group)
            for name, value in zip(self.rows, values, strict=True):
                self.rows[name].append(value)
            offset += len(ids)

    def taken(self) -> pa.RecordBatch:
        batch = pa.RecordBatch.from_pydict(self.rows, schema=PIECE)
        for column in self.rows.values():
            column.clear()
        return batch


def packed(docs: DataFrame, tokenizer_path: str, tiers: tuple[int, ...] = TIERS) -> DataFrame:
    """Pack ``docs(doc_id, text)``; one row per piece: doc_id, start, length, ids_crc32, doc_tokens,
    sequence_id, offset, tier (window length) and step_group (windows of one tier that make a
    training step of equal tokens).

    Every document ends with id 2; null and empty texts are that id alone. Repeated rows and null
    doc_ids are packed like others. Every id lies in exactly one piece; no windows are padded, since
    all lengths are powers of two. ``tokenizer_path``: a tokenizer file that all executors can read.
    """

    def run(batches):
        packer, encode = Packer(TaskContext.get().partitionId() << 33, tiers), WordTokenizer(tokenizer_path)
        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text")
            for at in range(0, len(ids), 128):
                part = [texts[i].as_py() or "" for i in range(at, min(at + 128, len(ids)))]
                for doc, tokens in zip(ids[at : at + 128], encode(part), strict=True):
                    packer.add(doc, tokens)
                if len(packer.rows["doc_id"]) > 20_000:
                    yield packer.taken()
        packer.finish()
        yield packer.taken()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECE_DDL)
