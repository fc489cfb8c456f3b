"""Operator 5: exact substring dedup with a column-wise multi-document suffix order.

A byte goes if it lies in a string of `length` bytes that also starts in a document with a
smaller doc_id. Such a string holds the place of a minimizer (the least hash of its
`gram`-byte pieces), and equal strings hold it at the same place. All strings that hold one
place of a minimizer make up its context.

Texts are bundled once, a few megabytes to a compressed row; rows of hashes and answers to
them name the bundle, so texts are never shuffled by document. What bundles ask is dealt by
hash into buckets, as packed arrays, and is made up beforehand, so that a hash has one entry
per bundle at most, however many documents hold it.

1. Which minimizer hashes do several documents hold? Asked with about 38 bits of each hash;
   hashes taken for shared by mistake only cost work.
2. Of a shared minimizer's context: which is the least document that has the same one (by
   128 bits)? In all others all its strings go. A string reaches far to one side at least;
   does any other context agree with this one on that side? If not, none shares a string.
3. The contexts that may share strings with others, each once, from its least document, are
   cut to what reaches far to the side they agree on, and dealt by that side. A task builds, block by block, the Burrows-Wheeler
   transform and common-prefix lengths of its distinct contexts column by column: each round
   inserts one symbol of every context, reading the round before from one sequential file
   and writing the next. Suffixes whose neighbours share `length` bytes form runs; a
   run's least document is the first holder of its string. A side that a crowd
   of contexts share is taken apart instead: each of its strings is grouped by itself.
4. Each bundle joins the covered ranges of its texts and hashes what is left.

Documents are UTF-8 bytes and strings never cross documents; judging uses the input only.
Edge cases: null text is empty; texts shorter than `length` keep everything; repetition
inside one document is no reason; rows repeated with the same doc_id are judged each and
never against each other; a row without doc_id is kept whole and judges none; extra columns
are ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import os
import tempfile
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.llm.common import cut, release_finished_shuffles, written

BASE = 0x100000001B3


@dataclass(frozen=True)
class Substrings:
    """length: bytes of a string; gram: bytes of a minimizer; block: contexts indexed together; crowd: contexts that share a side and are still indexed together; chunk: bytes of text hashed at once; bundle: bytes of texts that go together; bucket: hashes that meet in one bucket, about."""

    length: int = 50
    gram: int = 20
    block: int = 16_000
    crowd: int = 40_000
    chunk: int = 1 << 20
    bundle: int = 2 << 20
    bucket: int = 1_000_000

    @property
    def left(self) -> int:
        return self.length - self.gram

    @property
    def half(self) -> int:
        """A string reaches so far beyond its minimizer on one side at least."""
        return self.left // 2


def gram_hashes(b: np.ndarray, k: int) -> np.ndarray:
    """Mixed polynomial hashes of all k-byte pieces, by doubling."""
    h, power, n = b.astype(np.uint64) + np.uint64(1), BASE, 1
    out, have, rest = None, 0, k
    while rest:
        if rest & 1:  # append a piece of n bytes
            out = h if out is None else out[: len(b) - have - n + 1] * np.uint64(power) + h[have : have + len(b) - have - n + 1]
            have += n
        rest >>= 1
        if rest:
            h = h[:-n] * np.uint64(power) + h[n:]
            power, n = power * power % 2**64, 2 * n
    out = out ^ (out >> np.uint64(31))
    out = out * np.uint64(0x9E3779B97F4A7C15)
    return out ^ (out >> np.uint64(29))


def _slide(x: np.ndarray, w: int, f) -> np.ndarray:
    s = 1
    while 2 * s <= w:
        x, s = f(x[:-s], x[s:]), 2 * s
    return f(x[: len(x) - (w - s)], x[w - s :]) if s < w else x


def minimizers(text: bytes, cfg: Substrings, ends: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and places of the minimizers (all tied ones) of texts laid end to end."""
    n, k, w = len(text), cfg.gram, cfg.left + 1
    ends = np.array([n]) if ends is None else ends
    # strings that start so late in a text would cross into the next one
    late = np.zeros(n + 1, np.int32)
    np.add.at(late, np.maximum(np.r_[0, ends[:-1]], ends - cfg.length + 1), 1)
    np.add.at(late, ends, -1)
    late = np.cumsum(late)[:-1] > 0
    hs, ps = [], []
    with np.errstate(over="ignore"):
        for a in range(0, n - cfg.length + 1, cfg.chunk):
            # strings that start in a - left .. a + chunk hold the places a .. a + chunk
            lo, hi = max(0, a - cfg.left), min(n, a + cfg.chunk + cfg.length)
            h = np.maximum(gram_hashes(np.frombuffer(text, np.uint8, hi - lo, lo), k), np.uint64(1))
            least = _slide(h, w, np.minimum)
            least[late[lo : lo + len(least)]] = 0
            most = _slide(np.pad(least, (w - 1, w - 1)), w, np.maximum)
            end = a + cfg.chunk if a + cfg.chunk < n - cfg.length + 1 else n
            p = np.flatnonzero(most[a - lo : end - lo] == h[a - lo : end - lo]) + (a - lo)
            hs.append(h[p])
            ps.append(p + lo)
    if not hs:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    return np.concatenate(hs), np.concatenate(ps)


def mixed(*parts: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each row of byte matrices and number columns."""
    x = np.zeros(len(parts[0]), np.uint64)
    with np.errstate(over="ignore"):
        for part in parts:
            if part.ndim == 2:
                part = np.pad(part, ((0, 0), (0, -part.shape[1] % 8)))
                columns = np.ascontiguousarray(part).view(np.uint64).T
            else:
                columns = [part.astype(np.uint64)]
            for c in columns:
                x = (x ^ c) * np.uint64(0x9E3779B97F4A7C15)
                x ^= x >> np.uint64(32)
            x = x * np.uint64(0xD6E8FEB86659FD93)
            x ^= x >> np.uint64(29)
    return x


def _as_signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


# --- bundles ----------------------------------------------------------------------------


class Bundle:
    """Texts of some documents laid end to end: docs (0 where unknown), known, ends, text."""

    def __init__(self, blob: bytes):
        import zstandard

        raw = zstandard.decompress(blob)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        self.docs, self.ends = np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.int64, n, 8 + 8 * n)
        self.known = np.frombuffer(raw, np.uint8, n, 8 + 16 * n) > 0
        self.text = raw[8 + 17 * n :]
        self.starts = np.r_[0, self.ends[:-1]].astype(np.int64)

    @staticmethod
    def packed(docs: list, texts: list[bytes]) -> bytes:
        import zstandard

        head = [np.array([len(docs)], np.int64), np.array([d or 0 for d in docs], np.int64), np.cumsum([len(t) for t in texts], dtype=np.int64), np.array([d is not None for d in docs], np.uint8)]
        return zstandard.compress(b"".join([*[x.tobytes() for x in head], *texts]), 3)


def _bundle(cfg: Substrings):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        def row(docs: list, texts: list[bytes]) -> pa.RecordBatch:
            blob = Bundle.packed(docs, texts)
            chunk = xxh64_intdigest(blob) - (1 << 63)
            return pa.RecordBatch.from_arrays([pa.array([chunk], pa.int64()), pa.array([sum(map(len, texts))], pa.int64()), pa.array([blob], pa.binary())], names=["chunk", "size", "blob"])

        docs, texts, held = [], [], 0
        for batch in batches:
            for doc, value in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                docs.append(doc)
                texts.append((value.as_py() or "").encode())
                # a text takes its own room and that of its numbers
                held += len(texts[-1]) + 17
                if held >= cfg.bundle:
                    yield row(docs, texts)
                    docs, texts, held = [], [], 0
        if docs:
            yield row(docs, texts)

    return run


class Shared:
    """The minimizers of a bundle, and what buckets have said of them."""

    def __init__(self, bundle: Bundle, cfg: Substrings, bits: int):
        self.b, self.cfg, self.bits = bundle, cfg, bits
        h, p = minimizers(bundle.text, cfg, bundle.ends)
        owner = np.searchsorted(bundle.ends, p, side="right")
        known = bundle.known[owner]
        self.h, self.p, self.owner = h[known], p[known], owner[known]
        self.doc = bundle.docs[self.owner]

    def first_keys(self) -> Iterator[tuple[int, bytes]]:
        """(bucket, payload): distinct hashes, and whether several documents of the bundle have them."""
        keys, which = np.unique(self.h >> np.uint64(32 - self.bits), return_inverse=True)
        low, high = np.full(len(keys), np.iinfo(np.int64).max), np.full(len(keys), np.iinfo(np.int64).min)
        np.minimum.at(low, which, self.doc)
        np.maximum.at(high, which, self.doc)
        for bucket, at in dealt(keys >> np.uint64(32)):
            yield bucket, _sized(keys[at].astype(np.uint32), np.packbits(low[at] != high[at]))

    def keep_shared(self, replies: list) -> None:
        """Drops the minimizers that nobody shares, and works out the contexts of the others."""
        keys, which = np.unique(self.h >> np.uint64(32 - self.bits), return_inverse=True)
        flags = np.zeros(len(keys), bool)
        parts = {r["bucket"]: r["payload"] for r in replies or ()}
        for bucket, at in dealt(keys >> np.uint64(32)):
            flags[at] = np.unpackbits(np.frombuffer(parts[bucket], np.uint8), count=at.stop - at.start)
        keep = flags[which]
        self.h, self.p, self.owner, self.doc = (x[keep] for x in (self.h, self.p, self.owner, self.doc))
        cfg, b = self.cfg, self.b
        self.before = np.minimum(cfg.left, self.p - b.starts[self.owner])
        self.after = np.minimum(cfg.length, b.ends[self.owner] - self.p)
        data = np.frombuffer(b.text, np.uint8)
        c, left, right = (np.empty(len(self.p), np.uint64) for _ in range(3))
        for a in range(0, len(self.p), 50_000):
            part = slice(a, a + 50_000)
            at = self.p[part, None] + np.arange(-cfg.left, cfg.length)
            inside = (at >= (self.p - self.before)[part, None]) & (at < (self.p + self.after)[part, None])
            w = np.where(inside, data[np.clip(at, 0, max(0, len(data) - 1))], 0).astype(np.uint8)
            c[part] = mixed(w, self.before[part], self.after[part])
            h = self.h[part]
            left[part] = mixed(h, w[:, cfg.left - cfg.half : cfg.left + cfg.gram], np.full(len(h), 1))
            right[part] = mixed(h, w[:, cfg.left : cfg.left + cfg.gram + cfg.half], np.full(len(h), 2))
        # distinct contexts, with their least document here and one place of each
        order = np.lexsort((self.doc, c, self.h))
        fresh = np.r_[True, (self.h[order][1:] != self.h[order][:-1]) | (c[order][1:] != c[order][:-1])] if len(order) else np.zeros(0, bool)
        self.entry = np.empty(len(order), np.int64)
        self.entry[order] = np.cumsum(fresh) - 1
        one = order[fresh]
        self.one, self.eh, self.ec, self.first = one, self.h[one], c[one], self.doc[one]
        self.sides = [(left[one], self.before[one] >= cfg.half), (right[one], self.after[one] >= cfg.gram + cfg.half)]

    def _side(self, kind: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Distinct side hashes, the entries that have one, and which."""
        side, valid = self.sides[kind - 1]
        rows = np.flatnonzero(valid)
        keys, which = np.unique(side[rows], return_inverse=True)
        return keys, rows, which

    def second_keys(self) -> Iterator[tuple[int, int, bytes]]:
        """(kind, bucket, payload): kind 0 contexts with their least document, 1 and 2 sides with the least and greatest context and how many there are."""
        deal = mixed(self.eh, self.ec)
        order = np.argsort(deal, kind="stable")
        for bucket, at in dealt(deal[order] >> np.uint64(64 - self.bits) if self.bits else np.zeros(len(order), np.uint64)):
            rows = order[at]
            yield 0, bucket, _sized(self.eh[rows], self.ec[rows], self.first[rows])
        brief = (self.ec >> np.uint64(32)).astype(np.uint32)
        for kind in (1, 2):
            keys, rows, which = self._side(kind)
            low, high = np.full(len(keys), 2**32 - 1, np.uint32), np.zeros(len(keys), np.uint32)
            np.minimum.at(low, which, brief[rows])
            np.maximum.at(high, which, brief[rows])
            n = np.minimum(np.bincount(which, minlength=len(keys)), 65535).astype(np.uint16)
            for bucket, at in dealt(keys >> np.uint64(64 - self.bits) if self.bits else np.zeros(len(keys), np.uint64)):
                # 32 bits and the bucket: sides taken for one by mistake only cost work
                yield kind, bucket, _sized(keys[at].astype(np.uint32), low[at], high[at], n[at])

    def take_second(self, replies: list) -> None:
        """low: least document of each entry's context; open: by side, 0 nobody else agrees, 1 some do, 2 more than a block."""
        parts = {(r["kind"], r["bucket"]): r["payload"] for r in replies or ()}
        deal = mixed(self.eh, self.ec)
        order = np.argsort(deal, kind="stable")
        self.low = np.empty(len(order), np.int64)
        for bucket, at in dealt(deal[order] >> np.uint64(64 - self.bits) if self.bits else np.zeros(len(order), np.uint64)):
            self.low[order[at]] = np.frombuffer(parts[0, bucket], np.int64)
        self.open = []
        for kind in (1, 2):
            keys, rows, which = self._side(kind)
            said = np.zeros(len(keys), np.uint8)
            for bucket, at in dealt(keys >> np.uint64(64 - self.bits) if self.bits else np.zeros(len(keys), np.uint64)):
                said[at] = np.frombuffer(parts[kind, bucket], np.uint8)
            out = np.zeros(len(self.eh), np.uint8)
            out[rows] = said[which]
            self.open.append(out)

    def context(self, entry: int, kind: int = 0) -> tuple[int, bytes]:
        """An entry's context, for kind 1 or 2 the part that its strings reaching far to that side take; and how much later it starts."""
        i, cfg = self.one[entry], self.cfg
        p, before, after = int(self.p[i]), int(self.before[i]), int(self.after[i])
        start = min(before, cfg.left - cfg.half) if kind == 2 else before
        end = min(after, cfg.gram + cfg.left - cfg.half + cfg.left % 2) if kind == 1 else after
        return before - start, self.b.text[p - start : p + end]


def dealt(buckets: np.ndarray) -> Iterator[tuple[int, slice]]:
    """(bucket, its range) of sorted bucket numbers."""
    if len(buckets):
        cuts = np.r_[0, np.flatnonzero(buckets[1:] != buckets[:-1]) + 1, len(buckets)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            yield int(buckets[a]), slice(int(a), int(b))


def _sized(*columns: np.ndarray) -> bytes:
    return np.int64(len(columns[0])).tobytes() + b"".join(c.tobytes() for c in columns)


def _columns(payload: bytes, *types) -> list[np.ndarray]:
    n, at, out = int(np.frombuffer(payload, np.int64, 1)[0]), 8, []
    for t in types:
        out.append(np.frombuffer(payload, t, n, at))
        at += n * np.dtype(t).itemsize
    return out


# --- what bundles ask, and the answers --------------------------------------------------

ASKED = "kind int, bucket long, chunk long, payload binary"
ANSWERS = "array<struct<kind:int,bucket:bigint,payload:binary>>"


def _rows(rows: list[tuple], names: str) -> pa.RecordBatch:
    types = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "string": pa.string()}
    fields = [x.split() for x in names.split(", ")]
    columns = list(zip(*rows, strict=True)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, types[t]) for c, (_, t) in zip(columns, fields, strict=True)], names=[n for n, _ in fields])


def _bundles(batches: Iterator[pa.RecordBatch], cfg: Substrings, bits: int, said: int) -> Iterator[tuple[int, Shared, dict]]:
    """Each bundle with its minimizers; `said` of the two answers have been given and are taken in."""
    for batch in batches:
        for i in range(batch.num_rows):
            row = {n: batch.column(n)[i].as_py() for n in batch.schema.names}
            s = Shared(Bundle(row["blob"]), cfg, bits)
            if said >= 1:
                s.keep_shared(row["first"])
            if said >= 2:
                s.take_second(row["second"])
            yield row["chunk"], s, row


def _ask_first(cfg: Substrings, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk, s, _ in _bundles(batches, cfg, bits, 0):
            yield _rows([(0, bucket, chunk, payload) for bucket, payload in s.first_keys()], ASKED)

    return run


def _ask_second(cfg: Substrings, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk, s, _ in _bundles(batches, cfg, bits, 1):
            yield _rows([(kind, bucket, chunk, payload) for kind, bucket, payload in s.second_keys()], ASKED)

    return run


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, list[int], list[bytes]]]:
    """Rows come sorted by kind and bucket; one bucket is held at a time."""
    now, chunks, payloads = None, [], []
    for batch in batches:
        for kind, bucket, chunk, payload in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            if now != (kind, bucket):
                if now is not None:
                    yield *now, chunks, payloads
                now, chunks, payloads = (kind, bucket), [], []
            chunks.append(chunk)
            payloads.append(payload)
    if now is not None:
        yield *now, chunks, payloads


def _answer_first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for kind, bucket, chunks, payloads in _buckets(batches):
        keys = [_columns(p, np.uint32)[0] for p in payloads]
        several = [np.unpackbits(np.frombuffer(p, np.uint8, offset=8 + 4 * len(k)), count=len(k)) for p, k in zip(payloads, keys, strict=True)]
        every, which, n = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
        shared = (n > 1) | (np.bincount(which, np.concatenate(several), len(every)) > 0)
        said = np.split(shared[which], np.cumsum([len(k) for k in keys])[:-1])
        yield _rows([(kind, bucket, c, np.packbits(x).tobytes()) for c, x in zip(chunks, said, strict=True)], ASKED)


def _answer_second(cfg: Substrings):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for kind, bucket, chunks, payloads in _buckets(batches):
            parts = [_columns(p, np.uint64, np.uint64, np.int64) if kind == 0 else _columns(p, np.uint32, np.uint32, np.uint32, np.uint16) for p in payloads]
            columns = [np.concatenate(x) for x in zip(*parts, strict=True)]
            if kind == 0:
                h, c, doc = columns
                order = np.lexsort((doc, c, h))
                fresh = np.r_[True, (h[order][1:] != h[order][:-1]) | (c[order][1:] != c[order][:-1])]
                said = np.empty(len(h), np.int64)
                said[order] = doc[order][fresh][np.cumsum(fresh) - 1]
            else:
                keys, low, high, n = columns
                every, which = np.unique(keys, return_inverse=True)
                least, most = np.full(len(every), 2**32 - 1, np.uint32), np.zeros(len(every), np.uint32)
                np.minimum.at(least, which, low)
                np.maximum.at(most, which, high)
                many = np.bincount(which, n, len(every)) > cfg.crowd
                said = ((least != most) * (1 + many)).astype(np.uint8)[which]
            cuts = np.cumsum([len(p[0]) for p in parts])[:-1]
            yield _rows([(kind, bucket, k, x.tobytes()) for k, x in zip(chunks, np.split(said, cuts), strict=True)], ASKED)

    return run


class ColumnIndex:
    """Burrows-Wheeler transform and common prefixes of distinct byte strings, built column by column through files."""

    def __init__(self, strings: list[bytes], folder: str):
        self.m = m = len(strings)
        self.lengths = np.array([len(s) for s in strings])
        longest = int(self.lengths.max(initial=0))
        # column j holds the symbol before the suffix of length j, 0 if the suffix is the whole string
        padded = np.zeros((m, longest + 1), np.uint8)
        symbols = {c: i + 1 for i, c in enumerate(sorted(set(b"".join(strings))))}
        code = np.zeros(256, np.uint8)
        for c, i in symbols.items():
            code[c] = i
        if len(symbols) > 254:
            raise ValueError("too many symbols")  # UTF-8 text never has so many
        for i, s in enumerate(strings):
            padded[i, : len(s)] = code[np.frombuffer(s, np.uint8)[::-1]]
        self.files = [open(os.path.join(folder, f"{kind}{side}"), "w+b", buffering=0) for kind in ("transform", "prefix") for side in (0, 1)]  # noqa: SIM115
        self._write(0, np.ascontiguousarray(padded[:, 0]), np.zeros(m, np.uint8))
        at = np.arange(m)  # places of the suffixes inserted last, by string
        live = np.arange(m)
        for j in range(1, longest + 1):
            old, new = (j - 1) % 2, j % 2
            live = live[self.lengths[live] >= j]
            transform, prefix = self._read(old)
            place, order, ended = self._step(transform)
            fresh = place[at[live]]
            grown, common = self._insert(transform, prefix, fresh, order, ended, padded[live, j])
            self._write(new, grown, common)
            at[live] = fresh
        self.side = longest % 2

    def _write(self, side: int, transform: np.ndarray, prefix: np.ndarray) -> None:
        self.size = len(transform)
        for f, x in ((self.files[side], transform), (self.files[2 + side], prefix)):
            f.seek(0)
            f.write(memoryview(x))

    def _read(self, side: int) -> tuple[np.ndarray, np.ndarray]:
        out = []
        for f in (self.files[side], self.files[2 + side]):
            f.seek(0)
            out.append(np.frombuffer(f.read(self.size), np.uint8))
        return out[0], out[1]

    def close(self) -> None:
        for f in self.files:
            f.close()

    def _step(self, transform: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Where the suffix longer by one symbol stands (after the m empty suffixes), for every suffix; those whose symbol is 0 have none."""
        order = np.argsort(transform, kind="stable")
        ended = int((transform == 0).sum())
        place = np.full(len(transform), -1, np.int32)
        place[order[ended:]] = np.arange(self.m, self.m + len(order) - ended, dtype=np.int32)
        return place, order, ended

    def _insert(self, transform, prefix, fresh, order, ended, symbols) -> tuple[np.ndarray, np.ndarray]:
        n = self.m + len(order) - ended
        is_new = np.zeros(n, bool)
        is_new[fresh] = True
        grown, common = np.empty(n, np.uint8), np.empty(n, np.uint8)
        grown[~is_new], common[~is_new] = transform, prefix
        grown[fresh] = symbols
        values = np.append(prefix, np.uint8(0))
        # common prefix of neighbours p - 1 and p for each new p and each p after a new one
        for p in (fresh, fresh[fresh + 1 < n] + 1):
            common[p] = 0
            rank = p - self.m + ended
            ok = rank > ended
            x, y = order[rank[ok]], order[rank[ok] - 1]
            same = transform[x] == transform[y]
            p, x, y = p[ok][same], x[same], y[same]
            if len(p):
                # from the last range to the first, so that nothing is reduced between two ranges
                o = np.argsort(-x)
                p, x, y = p[o], x[o], y[o]
                ends = np.stack([y + 1, x + 1], axis=1).ravel()
                common[p] = np.minimum.reduceat(values, ends)[::2] + 1
        return grown, common

    def runs(self, least: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """For each suffix length from `least` on: string numbers, starts in the string, numbers of the run of suffixes that share `least` symbols."""
        transform, prefix = self._read(self.side)
        run = np.cumsum(prefix < least)
        place, _, _ = self._step(transform)
        at, live = np.arange(self.m), np.arange(self.m)
        for j in range(1, int(self.lengths.max(initial=0)) + 1):
            live = live[self.lengths[live] >= j]
            at[live] = place[at[live]]
            if j >= least:
                yield live, self.lengths[live] - j, run[at[live]]


def first_holders(strings: list[bytes], first: np.ndarray, least: int) -> list[np.ndarray]:
    """For each string and each start of a `least`-byte piece in it: the least `first` of the strings that hold the piece."""
    with tempfile.TemporaryDirectory(prefix="columns-") as folder:
        index = ColumnIndex(strings, folder)
        parts = list(index.runs(least))
        index.close()
    out = [np.empty(max(0, len(s) - least + 1), np.int64) for s in strings]
    if not parts:
        return out
    who, start, run = (np.concatenate(x) for x in zip(*parts, strict=True))
    o = np.argsort(run, kind="stable")
    cuts = np.flatnonzero(np.r_[True, np.diff(run[o]) > 0])
    lows = np.minimum.reduceat(first[who[o]], cuts)
    low = np.empty(len(run), np.int64)
    low[o] = np.repeat(lows, np.diff(np.r_[cuts, len(run)]))
    flat, ends = np.empty(sum(map(len, out)), np.int64), np.cumsum([0, *map(len, out)])
    flat[ends[who] + start] = low
    return [flat[ends[i] : ends[i + 1]] for i in range(len(out))]


OPEN = "side long, chunk long, ref long, at long, doc long, context binary"
MASKS = "chunk long, ref long, mask long"


def _open_contexts(cfg: Substrings, bits: int):
    """Contexts that may share strings with others, from their least document: what a side takes of them (at -1 less what it starts later), or string by string where a side has more than a block of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for chunk, s, _ in _bundles(batches, cfg, bits, 2):
            rows = []
            mine = s.low == s.first
            crowded = (s.open[0] == 2) | (s.open[1] == 2)
            for e in np.flatnonzero(mine & crowded):
                _, context = s.context(e)
                for at in range(len(context) - cfg.length + 1):
                    piece = context[at : at + cfg.length]
                    rows.append((xxh64_intdigest(piece) - (1 << 63), chunk, int(e), at, int(s.first[e]), piece))
            for kind in (1, 2):
                side = _as_signed(s.sides[kind - 1][0])
                for e in np.flatnonzero(mine & (s.open[kind - 1] == 1)):
                    later, context = s.context(e, kind)
                    if len(context) >= cfg.length:
                        rows.append((int(side[e]), chunk, int(e), -1 - later, int(s.first[e]), context))
            for a in range(0, len(rows), 50_000):
                yield _rows(rows[a : a + 50_000], OPEN)

    return run


def _index(cfg: Substrings):
    """Rows come sorted by side; blocks end between sides. Out: for each context the starts of strings that a smaller document has."""

    def block(rows: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(rows)
        doc, contexts = t["doc"].to_numpy(), t["context"].to_pylist()
        numbers: dict[bytes, int] = {}
        which = np.array([numbers.setdefault(c, len(numbers)) for c in contexts])
        first = np.full(len(numbers), np.iinfo(np.int64).max)
        np.minimum.at(first, which, doc)
        table = np.full((len(numbers), cfg.left + 1), np.iinfo(np.int64).max)
        for i, x in enumerate(first_holders(list(numbers), first, cfg.length)):
            table[i, : len(x)] = x
        mask = ((table[which] < doc[:, None]).astype(np.int64) << np.arange(cfg.left + 1)).sum(axis=1) << (-1 - t["at"].to_numpy())
        keep = mask != 0
        return pa.RecordBatch.from_arrays([pa.array(x[keep]) for x in (t["chunk"].to_numpy(), t["ref"].to_numpy(), mask)], names=["chunk", "ref", "mask"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        n, last = 0, None
        for batch in batches:
            side, begin = batch.column(0).to_numpy(), 0
            if not len(side):
                continue
            # where a block may end: before a row of another side
            cuts = np.flatnonzero(np.r_[bool(held) and side[0] != last, side[1:] != side[:-1]])
            while n + len(side) - begin > cfg.block:
                ends = cuts[(cuts > begin) | ((cuts == begin) & (n > 0))]
                if not len(ends):
                    break
                fit = ends[ends - begin <= cfg.block - n]
                end = int(fit[-1] if len(fit) else ends[0])
                held += [batch.slice(begin, end - begin)] if end > begin else []
                yield block(held)
                held, n, begin = [], 0, end
            held.append(batch.slice(begin))
            n, last = n + len(side) - begin, side[-1]
        if held:
            yield block(held)

    return run


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _apply(cfg: Substrings, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, s, row in _bundles(batches, cfg, bits, 2):
            b = s.b
            edge = np.zeros(len(b.text) + 1, np.int32)

            def cover(starts: np.ndarray, ends: np.ndarray, edge=edge) -> None:
                np.add.at(edge, starts, 1)
                np.add.at(edge, ends, -1)

            low = s.low[s.entry]
            start, end = s.p - s.before, s.p + s.after
            later = (s.doc > low) & (end - start >= cfg.length)
            cover(start[later], end[later])
            masks = np.zeros(len(s.eh), np.int64)
            for m in row["masks"] or ():
                masks[m["ref"]] |= m["mask"]
            mask = np.where(s.doc == low, masks[s.entry], 0) if len(s.eh) else np.zeros(0, np.int64)
            for at in range(cfg.left + 1):
                hit = start[(mask >> at) & 1 == 1] + at
                cover(hit, hit + cfg.length)
            gone = np.cumsum(edge)[:-1] > 0
            opens = gone & ~np.r_[False, gone[:-1]] if len(gone) else gone
            sums, spans = np.r_[0, np.cumsum(gone)], np.r_[0, np.cumsum(opens)]
            data, rows = np.frombuffer(b.text, np.uint8), []
            for doc, known, a, z in zip(b.docs.tolist(), b.known.tolist(), b.starts.tolist(), b.ends.tolist(), strict=True):
                removed = int(sums[z] - sums[a])
                kept = data[a:z][~gone[a:z]].tobytes() if removed else b.text[a:z]
                # a run that goes on from the text before starts anew here
                n = int(spans[z] - spans[a]) + int(a < z and gone[a] and not opens[a])
                rows.append((doc if known else None, z - a, removed, n, hashlib.sha256(kept).hexdigest()))
            yield _rows(rows, RESULT)

    return run


def substring_dedup(docs: DataFrame, cfg: Substrings = Substrings()) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc"), "text")
    bundles = cut(texts.mapInArrow(_bundle(cfg), "chunk long, size long, blob binary"))
    hashes = (bundles.agg(F.sum("size")).first()[0] or 0) // 10
    bits = min(32, (hashes // cfg.bucket).bit_length())
    asks = bundles.select("chunk", "blob")
    meet = lambda asked: asked.repartition("kind", "bucket").sortWithinPartitions("kind", "bucket")
    answers = lambda said, name: cut(said.groupBy("chunk").agg(F.collect_list(F.struct("kind", "bucket", "payload")).alias(name)))
    first = answers(meet(asks.mapInArrow(_ask_first(cfg, bits), ASKED)).mapInArrow(_answer_first, ASKED), "first")
    release_finished_shuffles(docs.sparkSession)
    told = asks.join(first, "chunk", "left")
    second = answers(meet(told.mapInArrow(_ask_second(cfg, bits), ASKED)).mapInArrow(_answer_second(cfg), ASKED), "second")
    release_finished_shuffles(docs.sparkSession)
    both = first.join(second, "chunk", "left")
    found = written(asks.join(both, "chunk", "left").mapInArrow(_open_contexts(cfg, bits), OPEN), "contexts")
    release_finished_shuffles(docs.sparkSession)
    indexed = found.filter("at < 0").repartition("side").sortWithinPartitions("side").mapInArrow(_index(cfg), MASKS)
    # sides that too many contexts share: each string by itself, its least document worked out before it is shuffled
    pieces = found.filter("at >= 0")
    least = pieces.groupBy("side", "context").agg(F.min("doc").alias("low"))
    single = pieces.join(least, ["side", "context"]).filter("low < doc").select("chunk", "ref", F.expr("shiftleft(1L, cast(at as int))").alias("mask"))
    masks = indexed.union(single).groupBy("chunk", "ref").agg(F.bit_or("mask").alias("mask"))
    masks = cut(masks.groupBy("chunk").agg(F.collect_list(F.struct("ref", "mask")).alias("masks")))
    release_finished_shuffles(docs.sparkSession)
    return asks.join(both.join(masks, "chunk", "left"), "chunk", "left").mapInArrow(_apply(cfg, bits), RESULT)
