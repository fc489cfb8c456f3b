"""Operator 1: language identification by a byte convolutional network.

Bytes of a fixed-length window are embedded, filters of several widths run over them, each
filter's largest response over the window feeds a softmax over the languages. Training is
plain numpy on the driver over a bounded sample of labelled rows (`sample` rows and
`windows` windows of each; the rows with the smallest seeded hash). A text is cut into all
of its windows, without overlap loss at the seams (windows overlap by the widest filter),
and the windows' log-probabilities are summed.

A filter over embedded bytes is linear, so at prediction time each width becomes sums of
look-ups in tables of byte-pair responses: a gather per pair of bytes instead of a product.

Edge cases: null texts and texts without a letter give `und` and score 0; with no labelled
row to learn from every text is `und`; repeated rows are predicted each; languages are the
labels seen in training; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"
UNKNOWN = "und"


@dataclass(frozen=True)
class ByteConv:
    """sample: most labelled rows read to the driver; windows: windows taken of each; length: bytes of a window; widths and filters: filters of each width; size: of a byte's embedding."""

    sample: int = 3000
    windows: int = 1
    length: int = 256
    widths: tuple[int, ...] = (2, 3, 4)
    filters: int = 12
    size: int = 8
    epochs: int = 6
    batch: int = 64
    rate: float = 0.02
    seed: int = 5


class ByteNet:
    """Parameters, training and prediction."""

    def __init__(self, cfg: ByteConv, langs: list[str]):
        self.cfg, self.langs = cfg, langs
        rng = np.random.default_rng(cfg.seed)
        draw = lambda *shape: rng.standard_normal(shape).astype(np.float32)
        self.p = {"emb": 0.5 * draw(256, cfg.size), "out": 0.1 * draw(len(cfg.widths) * cfg.filters, len(langs)), "bias": np.zeros(len(langs), np.float32)}
        for w in cfg.widths:
            self.p[f"conv{w}"] = draw(w * cfg.size, cfg.filters) / np.sqrt(w * cfg.size)
        self.p["emb"][0] = 0  # byte 0 pads

    def _columns(self, x: np.ndarray, w: int) -> np.ndarray:
        e = self.p["emb"][x]
        return np.concatenate([e[:, i : x.shape[1] - w + 1 + i] for i in range(w)], axis=2)

    def train(self, x: np.ndarray, y: np.ndarray) -> None:
        """Cross entropy by Adam; a max-pooled filter passes its gradient to the place of its maximum."""
        cfg, rng = self.cfg, np.random.default_rng(self.cfg.seed + 1)
        first, second = ({k: np.zeros_like(v) for k, v in self.p.items()} for _ in range(2))
        t = 0
        for _ in range(cfg.epochs):
            order = rng.permutation(len(x))
            for a in range(0, len(x), cfg.batch):
                at = order[a : a + cfg.batch]
                g = self._gradients(x[at], y[at])
                t += 1
                for k, d in g.items():
                    first[k] += 0.1 * (d - first[k])
                    second[k] += 0.001 * (d * d - second[k])
                    self.p[k] -= cfg.rate * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.999**t)) + 1e-8)
                self.p["emb"][0] = 0

    def _gradients(self, x: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        cfg, n = self.cfg, len(x)
        pooled, places = [], []
        for w in cfg.widths:
            r = self._columns(x, w) @ self.p[f"conv{w}"]
            places.append(r.argmax(axis=1))
            pooled.append(np.take_along_axis(r, places[-1][:, None], axis=1)[:, 0])
        h = np.maximum(np.concatenate(pooled, axis=1), 0)
        z = h @ self.p["out"] + self.p["bias"]
        z = np.exp(z - z.max(axis=1, keepdims=True))
        z /= z.sum(axis=1, keepdims=True)
        z[np.arange(n), y] -= 1
        z /= n
        g = {"out": h.T @ z, "bias": z.sum(axis=0), "emb": np.zeros_like(self.p["emb"])}
        back = (z @ self.p["out"].T) * (h > 0)
        for i, (w, at) in enumerate(zip(cfg.widths, places, strict=True)):
            d = back[:, i * cfg.filters : (i + 1) * cfg.filters]
            codes = x[np.arange(n)[:, None, None], at[:, :, None] + np.arange(w)]  # n, filters, w
            e = self.p["emb"][codes]
            g[f"conv{w}"] = np.einsum("nf,nfwd->wdf", d, e).reshape(w * cfg.size, cfg.filters)
            np.add.at(g["emb"], codes, d[:, :, None, None] * self.p[f"conv{w}"].reshape(w, cfg.size, cfg.filters).transpose(2, 0, 1)[None])
        return g

    def tables(self) -> tuple[np.ndarray, list[tuple[int, int, np.ndarray]]]:
        """One table of byte-pair responses for the first pair of all widths, and what later pairs (or a last byte) add: (column, place, table)."""
        heads, later = [], []
        for k, w in enumerate(self.cfg.widths):
            conv = self.p[f"conv{w}"].reshape(w, self.cfg.size, self.cfg.filters)
            single = [np.ascontiguousarray(self.p["emb"] @ c) for c in conv]
            pair = lambda i: (single[i][:, None] + single[i + 1][None]).reshape(65536, -1)  # noqa: B023, E731
            heads.append(pair(0))
            later += [(k, i, pair(i) if i + 1 < w else single[i]) for i in range(2, w, 2)]
        return np.ascontiguousarray(np.concatenate(heads, axis=1)), later

    def log_probabilities(self, x: np.ndarray, tables: tuple[np.ndarray, list]) -> np.ndarray:
        """Of windows x (rows). Places lie on the first axis, so that the pooling runs along whole rows of memory."""
        head, later = tables
        f, widest = self.cfg.filters, max(self.cfg.widths)
        x = np.ascontiguousarray(x.T)
        pairs = x[:-1].astype(np.int32) * 256 + x[1:]
        n = len(x) - widest + 1
        r = np.take(head, pairs[:n], axis=0, mode="clip")
        for k, i, part in later:
            r[:, :, k * f : (k + 1) * f] += np.take(part, (pairs if len(part) == 65536 else x)[i : i + n], axis=0, mode="clip")
        z = np.maximum(r.max(axis=0), 0) @ self.p["out"] + self.p["bias"]
        z = z - z.max(axis=1, keepdims=True)
        return z - np.log(np.exp(z).sum(axis=1, keepdims=True))


def windows_of(text: bytes, cfg: ByteConv) -> np.ndarray:
    """All windows of a text as rows of bytes, zero padded, each starting where a filter of the one before could not reach."""
    step = cfg.length - max(cfg.widths) + 1
    n = max(1, -(-len(text) // step))
    buffer = np.zeros((n - 1) * step + cfg.length, np.uint8)
    buffer[: len(text)] = np.frombuffer(text, np.uint8)
    return np.lib.stride_tricks.sliding_window_view(buffer, cfg.length)[::step]


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def training_rows(docs: DataFrame, cfg: ByteConv) -> list:
    """At most cfg.sample labelled rows: those with the smallest seeded hash. Counted first, so that tasks offer few more in all than are taken."""
    labelled = docs.filter(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    n = labelled.select("doc_id").count()
    share = min(1.0, (1.2 * cfg.sample + 300) / max(1, n))
    h = F.xxhash64(F.lit(cfg.seed + 1), "doc_id")
    rows = labelled.filter(F.col("text").isNotNull() & (h <= F.lit(int(-(2**63) + share * (2**64 - 1025)))))
    start = F.pmod(F.xxhash64(F.lit(cfg.seed), "doc_id"), F.greatest(F.length("text") - cfg.length, F.lit(0)) + 1).cast("int") + 1
    cut = rows.select(h.alias("h"), "doc_id", "lang", F.substring("text", start, F.lit(cfg.length)).alias("text"))
    return cut.orderBy("h", "doc_id", "lang", "text").limit(cfg.sample).collect()


def fit(docs: DataFrame, cfg: ByteConv = ByteConv()) -> ByteNet | None:
    rows = training_rows(docs, cfg)
    langs = sorted({r.lang for r in rows})
    if not langs:
        return None
    net = ByteNet(cfg, langs)
    x = np.stack([windows_of(r.text.encode()[: cfg.length], cfg)[0] for r in rows])
    net.train(x, np.array([langs.index(r.lang) for r in rows]))
    return net


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text[:64])) or any(map(str.isalpha, text[64:]))


def _predictor(net: ByteNet | None, most: int = 64):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = net.tables() if net else None
        for batch in batches:
            texts = [t.as_py() for t in batch.column(2)]
            usable = [net is not None and t is not None and has_letter(t) for t in texts]
            sums = np.zeros((len(texts), len(net.langs) if net else 1))
            counts = np.zeros(len(texts))
            rows: list[np.ndarray] = []
            owners: list[int] = []

            def flush() -> None:
                x, who = np.concatenate(rows), np.asarray(owners)  # noqa: B023
                for a in range(0, len(x), most):
                    np.add.at(sums, who[a : a + most], net.log_probabilities(x[a : a + most], tables))  # noqa: B023
                np.add.at(counts, who, 1)  # noqa: B023
                rows.clear()  # noqa: B023
                owners.clear()  # noqa: B023

            for i, (text, ok) in enumerate(zip(texts, usable, strict=True)):
                if ok:
                    w = windows_of(text.encode(), net.cfg)
                    rows.append(w)
                    owners += [i] * len(w)
                    if len(owners) >= 64 * most:
                        flush()
            if owners:
                flush()
            mean = sums / np.maximum(counts, 1)[:, None]
            best = sums.argmax(axis=1)
            e = np.exp(mean - mean.max(axis=1, keepdims=True))
            score = (e.max(axis=1) / e.sum(axis=1)).clip(0, 1)
            langs = [net.langs[b] if ok else UNKNOWN for b, ok in zip(best, usable, strict=True)]
            scores = [float(s) if ok else 0.0 for s, ok in zip(score, usable, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return run


def identify(docs: DataFrame, cfg: ByteConv = ByteConv(), net: ByteNet | None = None) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score. Trains on docs unless a network is given."""
    net = net or fit(docs, cfg)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text")
    return rows.mapInArrow(_predictor(net), SCHEMA)


def accepted(docs: DataFrame, least: float = 0.3, cfg: ByteConv = ByteConv()) -> DataFrame:
    """The documents, all columns as they are, whose language is known with at least this score."""
    net = fit(docs.select("doc_id", "text", "lang"), cfg)
    predict, names = _predictor(net), docs.columns
    # Arrow functions take columns by name, so names that would have to be quoted are put aside
    plain = docs.toDF(*[f"c{i}" for i in range(len(names))])
    at = (names.index("doc_id"), names.index("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            probe = pa.RecordBatch.from_arrays([batch.column(at[0]), pa.nulls(batch.num_rows, pa.bool_()), batch.column(at[1])], names=["a", "b", "c"])
            for out in predict(iter([probe])):
                keep = np.asarray(out.column(3)) >= least
                yield batch.filter(pa.array(keep))

    return plain.mapInArrow(run, plain.schema).toDF(*names)
