"""Operator 2: packing token pieces into windows by non-negative least squares.

Each input partition is packed on its own, in blocks of bounded size, while its texts are
being tokenized: nothing is shuffled. A document longer than the window gives full windows
at once; its rest is a piece. For the rests of a block a histogram over length classes is
taken, shallow combinations of classes that fill a window are enumerated, their repeat
counts are solved by non-negative least squares against the histogram, rounded down, and
filled with pieces of those classes. What is left over is packed greedily, longest first;
a gap too short for any whole piece is closed by cutting one. The last window of a
partition is cut into power-of-two sequences, so it needs no padding.

A word's token ids depend on the word alone in this vocabulary (white space dropped,
pieces of a word merged among themselves), so ids are looked up per normalised word in a
bounded cache; texts with characters outside a plain range go through the tokenizer whole.

Edge cases: a null or empty text is the single end id; repeated rows are packed each;
extra columns are ignored; an empty table gives an empty result. sequence_id is unique
over the result: partition number in the high bits, a counter in the low ones.
"""

from __future__ import annotations

import itertools
import re
import unicodedata
import zlib
from collections import defaultdict
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

WINDOW = 2048
END_ID = 1
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


@dataclass(frozen=True)
class Packing:
    """window: tokens of a sequence; classes: length classes of the histogram; depth: most pieces in a combination; block: rests solved together; cache: words kept with their ids; characters: bytes of text tokenized together; slack: gap (tokens) that is closed by cutting a piece if no whole one fits."""

    window: int = WINDOW
    classes: int = 24
    depth: int = 3
    block: int = 20_000
    cache: int = 400_000
    characters: int = 4_000_000
    slack: int = 0


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordIds:
    """Token ids of texts as little-endian unsigned 32-bit bytes."""

    #: Characters whose normalisation, case and class agree between Python and the tokenizer.
    plain = re.compile(r"[\t\n\r\x20-\x7e\xa1-\xa9\xab-\xb1\xb4\xb6-\xb8\xbb\xbf-įĲ-ž]*\Z")
    #: A normalised text's words: the vocabulary's split pattern for the plain characters.
    word = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+")

    def __init__(self, path: str, keep: int):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.keep = keep
        self.known: dict[str, bytes] = {}

    def _learn(self, words: list[str]) -> dict[str, bytes]:
        """Ids of new words, many at once: they are encoded as one text, and its tokens say which word they are of."""
        out: dict[str, bytes] = {}
        for a in range(0, len(words), 512):
            part = words[a : a + 512]
            e = self.whole.encode(" ".join(part), add_special_tokens=False)
            ids, of = np.asarray(e.ids, "<u4"), np.asarray(e.word_ids)
            if len(ids) and of[-1] == len(part) - 1:
                ends = np.searchsorted(of, np.arange(len(part) + 1))
                out.update((w, ids[ends[i] : ends[i + 1]].tobytes()) for i, w in enumerate(part))
            else:  # a word that isn't one piece of the vocabulary's split: each on its own
                out.update((w, self.one(w)) for w in part)
        return out

    def one(self, text: str) -> bytes:
        return np.asarray(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def batch(self, texts: list[str]) -> list[bytes]:
        """The ids of each text. Words new to the cache are learnt together; a full cache starts anew."""
        split = [None if "<|" in t or not self.plain.match(t) else self.word.findall(unicodedata.normalize("NFC", t).lower()) for t in texts]
        new = set().union(*(x for x in split if x is not None)).difference(self.known)
        if len(self.known) + len(new) > self.keep:
            self.known = {}
            new = set().union(*(x for x in split if x is not None))
        self.known.update(self._learn(sorted(new)))
        ids = self.known.__getitem__
        return [self.one(t) if x is None else b"".join(map(ids, x)) for t, x in zip(texts, split, strict=True)]

    def __call__(self, text: str) -> bytes:
        return self.batch([text])[0]


_workers: dict[tuple[str, int], WordIds] = {}


def word_ids(path: str, keep: int) -> WordIds:
    """One cache for all tasks that a Python worker runs."""
    if (path, keep) not in _workers:
        _workers[path, keep] = WordIds(path, keep)
    return _workers[path, keep]


def combinations(sizes: np.ndarray, window: int, depth: int) -> np.ndarray:
    """Columns of class counts: combinations of up to depth pieces that fit a window and waste less than the smallest class, plus a single piece of each class."""
    k = len(sizes)
    out = []
    for d in range(1, depth + 1):
        for c in itertools.combinations_with_replacement(range(k), d):
            total = sizes[list(c)].sum()
            if total <= window and (d == 1 or total + sizes[0] > window):
                out.append(np.bincount(c, minlength=k))
    return np.asarray(out, float).T


def nnls(a: np.ndarray, b: np.ndarray, rounds: int = 300) -> np.ndarray:
    """x >= 0 with least |a x - b|: an active-set search; passive columns are freed one by one by steepest gain and dropped where they turn negative."""
    gram, target = a.T @ a, a.T @ b
    x = np.zeros(a.shape[1])
    passive = np.zeros(a.shape[1], bool)
    tolerance = 1e-9 * max(1.0, np.abs(target).max(initial=0.0))
    for _ in range(rounds):
        gain = target - gram @ x
        gain[passive] = -np.inf
        j = int(gain.argmax())
        if gain[j] <= tolerance:
            break
        passive[j] = True
        while True:
            at = np.flatnonzero(passive)
            z = np.linalg.lstsq(gram[np.ix_(at, at)], target[at], rcond=None)[0]
            if (z > 0).all():
                x[:] = 0
                x[at] = z
                break
            low = z <= 0
            step = (x[at][low] / np.maximum(x[at][low] - z[low], 1e-300)).min()
            x[at] += step * (z - x[at])
            passive[at[x[at] <= 1e-12]] = False
            x[~passive] = 0
            if not passive.any():
                break
    return x


def plan_windows(lengths: np.ndarray, cfg: Packing) -> tuple[list[list[int]], list[int]]:
    """Whole pieces to windows by the solved combinations; returns windows (lists of piece numbers) and the pieces left over."""
    width = cfg.window // cfg.classes
    klass = np.minimum((lengths + width - 1) // width, cfg.classes) - 1
    sizes = np.minimum(np.arange(1, cfg.classes + 1) * width, cfg.window)
    sizes[-1] = cfg.window
    columns = combinations(sizes, cfg.window, cfg.depth)
    counts = np.bincount(klass, minlength=cfg.classes).astype(float)
    repeats = np.floor(nnls(columns, counts) + 1e-6).astype(int)
    order = np.argsort(klass, kind="stable")
    pools = np.split(order, np.cumsum(np.bincount(klass, minlength=cfg.classes))[:-1])
    pools = [list(p) for p in pools]
    windows = []
    for c in np.flatnonzero(repeats):
        need = [(k, int(n)) for k, n in enumerate(columns[:, c]) if n]
        if need[0][0] + 1 == cfg.classes or sum(n for _, n in need) < 2:
            continue  # a lone piece is left to the greedy part, which may join others to it
        for _ in range(repeats[c]):
            if any(len(pools[k]) < n for k, n in need):
                break
            windows.append([pools[k].pop() for k, n in need for _ in range(n)])
    return windows, [i for p in pools for i in p]


class Packer:
    """Sequences of one partition. Gets documents, yields rows of placed pieces; holds one block of rests."""

    def __init__(self, cfg: Packing, first_sequence: int):
        self.cfg, self.sequence = cfg, first_sequence
        self.rests: list[tuple] = []  # doc_id, start, bytes, doc_tokens

    def _row(self, piece: tuple, offset: int) -> tuple:
        doc_id, start, ids, total = piece
        return doc_id, start, len(ids) // 4, zlib.crc32(ids), total, self.sequence, offset

    def add(self, doc_id, ids: bytes) -> Iterator[tuple]:
        total, w = len(ids) // 4, self.cfg.window
        for start in range(0, total - w + 1, w):
            yield self._row((doc_id, start, ids[4 * start : 4 * (start + w)], total), 0)
            self.sequence += 1
        if total % w:
            start = total - total % w
            self.rests.append((doc_id, start, ids[4 * start :], total))
        if len(self.rests) >= self.cfg.block:
            yield from self.flush(False)

    def _fill(self, pieces: list[tuple], pool: dict[int, list[tuple]], lengths: list[int]) -> Iterator[tuple]:
        """One window from these pieces, topped up from the pool (pieces by length)."""
        import bisect

        offset = 0
        for p in pieces:
            yield self._row(p, offset)
            offset += len(p[2]) // 4
        while offset < self.cfg.window and lengths:
            gap = self.cfg.window - offset
            i = bisect.bisect_right(lengths, gap) - 1
            if i >= 0:
                p = pool[lengths[i]].pop()
                if not pool[lengths[i]]:
                    del pool[lengths[i]]
                    lengths.pop(i)
            elif gap > self.cfg.slack:  # every piece is longer than the gap: cut the shortest
                n = lengths[0]
                doc_id, start, ids, total = pool[n].pop()
                if not pool[n]:
                    del pool[n]
                    lengths.pop(0)
                p = (doc_id, start, ids[: 4 * gap], total)
                if n - gap not in pool:
                    bisect.insort(lengths, n - gap)
                pool[n - gap].append((doc_id, start + gap, ids[4 * gap :], total))
            else:
                break
            yield self._row(p, offset)
            offset += len(p[2]) // 4
        self.sequence += 1

    def flush(self, last: bool) -> Iterator[tuple]:
        if not self.rests:
            return
        sizes = np.array([len(p[2]) // 4 for p in self.rests])
        windows, left = plan_windows(sizes, self.cfg)
        pool: dict[int, list[tuple]] = defaultdict(list)
        for i in left:
            pool[int(sizes[i])].append(self.rests[i])
        lengths = sorted(pool)
        total = int(sizes[left].sum()) if left else 0
        for w in windows:
            whole = [self.rests[i] for i in w]
            # the pool may run short for topping up only in a partition's last block
            yield from self._fill(whole, pool, lengths)
        while lengths and (total := sum(n * len(pool[n]) for n in lengths)) >= self.cfg.window:
            yield from self._fill([], pool, lengths)
        self.rests = [p for n in lengths for p in pool[n]]
        if last:
            yield from self._binary()

    def _binary(self) -> Iterator[tuple]:
        """The rests as sequences whose sizes are powers of two, largest first."""
        pieces = self.rests[::-1]
        left = sum(len(p[2]) // 4 for p in pieces)
        while left:
            room, offset = min(self.cfg.window, 1 << (left.bit_length() - 1)), 0
            left -= room
            while room:
                doc_id, start, ids, total = pieces.pop()
                n = min(room, len(ids) // 4)
                yield self._row((doc_id, start, ids[: 4 * n], total), offset)
                if 4 * n < len(ids):
                    pieces.append((doc_id, start + n, ids[4 * n :], total))
                room, offset = room - n, offset + n
            self.sequence += 1
        self.rests = []


def slices(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts (column 1) have about so many bytes together, at least one row each."""
    sizes = np.nan_to_num(pc.binary_length(batch.column(1)).to_numpy(zero_copy_only=False).astype(float))
    ends = np.flatnonzero(np.diff(np.cumsum(sizes) // most, prepend=0) > 0)
    for a, b in zip([0, *ends], [*ends, batch.num_rows], strict=True):
        if b > a:
            yield batch.slice(a, b - a)


def _packer(path: str, cfg: Packing) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    names = [x.split()[0] for x in SCHEMA.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        ids, packer = word_ids(path, cfg.cache), Packer(cfg, TaskContext.get().partitionId() << 40)
        end = np.array([END_ID], "<u4").tobytes()

        def out(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=names)

        for batch in batches:
            rows: list[tuple] = []
            for part in slices(batch, cfg.characters):
                texts = [t or "" for t in part.column(1).to_pylist()]
                for doc_id, found in zip(part.column(0).to_pylist(), ids.batch(texts), strict=True):
                    rows.extend(packer.add(doc_id, found + end))
                if len(rows) > 20_000:
                    yield out(rows)
                    rows = []
            if rows:
                yield out(rows)
        rows = list(packer.flush(True))
        if rows:
            yield out(rows)

    return run


def pack(docs: DataFrame, cfg: Packing = Packing(), path: str | None = None) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    return docs.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(_packer(path or tokenizer_path(), cfg), SCHEMA)
