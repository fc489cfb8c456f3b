"""Operator 7: exact Jaccard join on word n-grams by grouped prefixes, and its components.

1. A pass over the texts hashes each document's distinct word n-grams to 64 bits.
   Documents with the same set collapse to their least doc_id (set digest).
2. n-grams that are frequent somewhere are counted (each task reports those it has seen
   several times; the most frequent of the sums, a bounded number, are broadcast). They go
   last in the order in which a set is sorted, so prefixes hold rare n-grams. The order is
   total whatever the counts, so it never decides about results, only about work. How many
   counts there are is known before the list is collected, and bounds it.
3. Sets with equal prefixes and equal size collapse into one group. Groups that share a
   prefix n-gram, have compatible sizes, whose elements from that n-gram on are enough for
   the common part that the similarity asks for, and whose parity words do not differ in more
   bits than it allows elements to differ are candidates. (A set's parity words hold,
   for each of PARITY_BITS buckets, whether it has an odd number of elements there: one
   element that only one of two sets has changes one bit.)
4. Candidates are taken in two rounds, so that a family of near copies never becomes all of
   its pairs. First each group is paired only with the next one in the posting list of each
   n-gram, and with its own members; verified links are joined to components. Then the
   posting lists are compared in full, but only across different components.
5. Pairs pass a wider parity sketch, as long as its set, and are then verified on the full
   sets, recomputed from the texts of the documents that occur in pairs; the links that hold
   join the components.

Links between documents of one component that are implied by others are not looked for.

Edge cases: null, empty and blank texts have no set, link with nothing and are their own
component; a text with fewer words than n has its whole word sequence as its one n-gram;
repeated rows with one doc_id count as one document with that id; extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.llm.common import cut, release_finished_shuffles
from stagefilter.llm.components import components

PARITY_WORDS = 8
PARITY_BITS = 64 * PARITY_WORDS
UPPER_TO_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


@dataclass(frozen=True)
class JaccardJoin:
    """n: words of an n-gram; percent: least similarity; local: times a task sees an n-gram before it reports it; frequent: most n-grams in the broadcast list (16 bytes each); broadcast_ids: most doc_ids that are broadcast to pick texts, more are joined by shuffling."""

    n: int = 3
    percent: int = 90
    local: int = 4
    frequent: int = 500_000
    broadcast_ids: int = 2_000_000


def ngram_set(text: str | None, n: int) -> np.ndarray:
    """Sorted distinct hashes of a text's word n-grams."""
    from xxhash import xxh64_intdigest

    ws = (text or "").encode("utf-8", "surrogatepass").translate(UPPER_TO_LOWER).split()
    if not ws:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxh64_intdigest, ws), np.uint64, len(ws))
    m = max(1, len(h) - n + 1)
    out = np.full(m, min(len(h), n), np.uint64)
    with np.errstate(over="ignore"):
        for i in range(min(n, len(h))):
            out = (out ^ h[i : i + m]) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(29)
    return np.unique(out)


def parity(grams: np.ndarray) -> np.ndarray:
    odd = np.bincount((grams % np.uint64(PARITY_BITS)).astype(np.int64), minlength=PARITY_BITS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def sketch(grams: np.ndarray) -> bytes:
    """Parities over two to four buckets for each element, a power of two of them."""
    width = 1 << max(8, int(2 * len(grams) - 1).bit_length())
    odd = np.bincount(((grams >> np.uint64(20)) % np.uint64(width)).astype(np.int64), minlength=width) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def least_apart(a: bytes, b: bytes) -> int:
    """A lower bound of the number of elements that only one of two sets has. The longer sketch is folded to the shorter one's buckets."""
    x, y = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
    while len(x) > len(y):
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


def _text(value) -> str | None:
    return value.as_py()


def prefix_length(size: int, percent: int) -> int:
    """A set of this size must share one of so many first elements with any set it links to."""
    return size - (size * percent + 99) // 100 + 1


class Order:
    """Total order of n-grams: those not in the list first, by hash; then the list by count."""

    def __init__(self, grams: np.ndarray, counts: np.ndarray):
        by = np.argsort(grams)
        self.grams, self.counts = grams[by], counts[by]

    def first(self, grams: np.ndarray, n: int) -> np.ndarray:
        if len(self.grams):
            at = np.minimum(np.searchsorted(self.grams, grams), len(self.grams) - 1)
            weight = np.where(self.grams[at] == grams, self.counts[at], 0)
            grams = grams[np.lexsort((grams, weight))]
        return grams[:n]


def _frequent(cfg: JaccardJoin):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def report() -> pa.RecordBatch:
            g, c = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(g[c >= cfg.local].view(np.int64)), pa.array(c[c >= cfg.local])], names=["gram", "n"])

        for batch in batches:
            for value in batch.column(0):
                held.append(ngram_set(_text(value), cfg.n))
                n += len(held[-1])
                if n > 4_000_000:
                    yield report()
                    held, n = [], 0
        if held:
            yield report()

    return run


def frequent_grams(docs: DataFrame, cfg: JaccardJoin) -> Order:
    """The n-grams of the highest classes of counts (powers of two) that together hold at most cfg.frequent n-grams."""
    seen = cut(docs.select("text").mapInArrow(_frequent(cfg), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")))
    level = F.floor(F.log2("n"))
    least, total = 64, 0
    for r in sorted(seen.groupBy(level.alias("level")).count().collect(), key=lambda r: -r.level):
        total += r["count"]
        if total > cfg.frequent:
            break
        least = r.level
    rows = seen.filter(level >= least).toArrow()
    return Order(rows["gram"].to_numpy().view(np.uint64), rows["n"].to_numpy())


def _sets(cfg: JaccardJoin, order):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, digests, firsts, odd, wide = [], [], [], [], []
            for value in batch.column(1):
                s = ngram_set(_text(value), cfg.n)
                sizes.append(len(s))
                digests.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                p = order.value.first(s, prefix_length(len(s), cfg.percent)) if len(s) else s
                firsts.append(p.view(np.int64))
                odd.append(parity(s))
                wide.append(sketch(s))
            offsets = np.cumsum([0, *map(len, firsts)]).astype(np.int32)
            flat = np.concatenate(firsts) if firsts else np.empty(0, np.int64)
            columns = [batch.column(0), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))]
            columns += [pa.array(wide, pa.binary()), *[pa.array(w) for w in np.asarray(odd, np.int64).reshape(-1, PARITY_WORDS).T]]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "size", "digest", "grams", "sketch", *PARITY])

    return run


PARITY = [f"p{i}" for i in range(PARITY_WORDS)]
SETS = "doc_id long, size long, digest binary, grams array<long>"
PREFIXES = SETS + ", sketch binary" + "".join(f", {p} long" for p in PARITY)


def _compatible(x: str, y: str, percent: int):
    """Whether two sets can be similar enough by their sizes and parity words. x, y: prefixes of the column names."""
    sx, sy = F.col(f"{x}size"), F.col(f"{y}size")
    apart = F.lit(0)
    for p in PARITY:
        apart = apart + F.bit_count(F.col(f"{x}{p}").bitwiseXOR(F.col(f"{y}{p}")))
    sizes = (100 * sx >= percent * sy) & (100 * sy >= percent * sx)
    return sizes & ((100 + percent) * apart <= (100 - percent) * (sx + sy))


def _sketched(cfg: JaccardJoin):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, sa, sb, x, y = (c.to_pylist() for c in batch.columns)
            keep = [(100 + cfg.percent) * least_apart(p, q) <= (100 - cfg.percent) * (m + n) for m, n, p, q in zip(sa, sb, x, y, strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _verify(cfg: JaccardJoin):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                a, b = ngram_set(_text(x), cfg.n), ngram_set(_text(y), cfg.n)
                both = len(np.intersect1d(a, b, assume_unique=True))
                keep.append(100 * both >= cfg.percent * (len(a) + len(b) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def _linked(pairs: DataFrame, docs: DataFrame, member: DataFrame, cfg: JaccardJoin) -> DataFrame:
    """The pairs (a, b) of doc_ids whose sets are similar enough."""
    side = lambda x: member.select(F.col("rep").alias(x), F.col("size").alias(f"{x}size"), F.col("sketch").alias(f"{x}sketch"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "asize", "bsize", "asketch", "bsketch")
    near = cut(both.mapInArrow(_sketched(cfg), "a long, b long"))
    needed = cut(near.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct())
    if needed.count() <= cfg.broadcast_ids:
        needed = F.broadcast(needed)
    # rows repeated with one doc_id would pair with each other's texts: one text each
    texts = docs.join(needed, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    left = near.join(texts.toDF("a", "ta"), "a")
    return left.join(texts.toDF("b", "tb"), "b").select("a", "b", "ta", "tb").mapInArrow(_verify(cfg), "a long, b long")


def jaccard_classes(docs: DataFrame, cfg: JaccardJoin = JaccardJoin()) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id."""
    spark = docs.sparkSession
    texts = docs.selectExpr("cast(doc_id as bigint) doc_id", "text")
    order = spark.sparkContext.broadcast(frequent_grams(texts, cfg))
    sets = cut(texts.mapInArrow(_sets(cfg, order), PREFIXES))
    # equal sets: one representative each
    kinds = sets.filter("size > 0").groupBy("digest", "size", "grams", "sketch", *PARITY).agg(F.min("doc_id").alias("rep"))
    # equal prefixes and sizes: one group each, named by its least representative
    group = Window.partitionBy("size", "grams")
    member = cut(kinds.withColumn("gid", F.min("rep").over(group)).withColumn("members", F.count("*").over(group)))
    # postings that more than one set has, each with the one before it
    groups = member.filter("rep = gid").select("gid", "members", "size", F.posexplode("grams").alias("at", "gram"))
    listed = Window.partitionBy("gram").orderBy("size", "gid")
    shared = groups.select("gram", "gid", "size", "at", F.sum("members").over(Window.partitionBy("gram")).alias("sets"), F.lag("gid").over(listed).alias("a"), F.lag("size").over(listed).alias("asize"))
    posted = cut(shared.filter("sets > 1").drop("sets"))
    # first round: neighbours in posting lists, members of a group against its first
    chain = posted.filter(F.col("a").isNotNull() & (100 * F.col("asize") >= cfg.percent * F.col("size"))).select("a", F.col("gid").alias("b"))
    inner = member.filter("rep <> gid").select(F.col("gid").alias("a"), F.col("rep").alias("b"))
    words = lambda x: member.select(F.col("rep").alias(x), *[F.col(c).alias(f"{x}_{c}") for c in ("size", *PARITY)])
    chain = chain.union(inner).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    tried = cut(chain.join(words("a"), "a").join(words("b"), "b").filter(_compatible("a_", "b_", cfg.percent)).select("a", "b"))
    links = cut(_linked(tried, texts, member, cfg))
    near = components(links)
    # second round: full posting lists, across components only; all members stand for themselves
    of = member.join(near, F.col("rep") == F.col("node"), "left").select("rep", "gid", "size", *PARITY, F.coalesce("component", "rep").alias("c"))
    named = of.select("gid", F.col("rep").alias("r"), "c")
    lists = posted.select("gram", "gid").join(named, "gid")
    mixed = lists.groupBy("gram").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo < hi").select("gram")
    wide = posted.select("gram", "gid", "at").join(mixed, "gram", "left_semi").join(of, "gid").select("gram", "at", "rep", "c", "size", *PARITY)
    x, y = (wide.select("gram", *[F.col(k).alias(f"{side}_{k}") for k in ("at", "rep", "c", "size", *PARITY)]) for side in "xy")
    # what two sets share starts with one n-gram, and is no more than either has from there on
    enough = [(100 + cfg.percent) * (F.col(f"{s}_size") - F.col(f"{s}_at")) >= cfg.percent * (F.col("x_size") + F.col("y_size")) for s in "xy"]
    fits = (F.col("x_c") != F.col("y_c")) & enough[0] & enough[1] & (F.col("x_rep") < F.col("y_rep")) & _compatible("x_", "y_", cfg.percent)
    rest = x.withColumnRenamed("gram", "x_gram").join(y, (F.col("x_gram") == F.col("gram")) & fits).select(F.col("x_rep").alias("a"), F.col("y_rep").alias("b")).distinct()
    rest = cut(rest.join(tried, ["a", "b"], "left_anti"))
    release_finished_shuffles(docs.sparkSession)
    late = _linked(rest, texts, member, cfg)
    found = components(links.union(late))
    named = member.select("digest", "size", "rep").join(found, F.col("rep") == F.col("node"), "left").select("digest", "size", F.coalesce("component", "rep").alias("component"))
    # components are named by representatives, and those are the least doc_ids of their sets
    out = sets.select("doc_id", "size", "digest").join(named, ["digest", "size"], "left")
    return out.select("doc_id", F.col("size").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))


def one_per_class(docs: DataFrame, cfg: JaccardJoin = JaccardJoin()) -> DataFrame:
    """The documents, all columns as they are, whatever their names, that are the least of their class."""
    first = jaccard_classes(docs.select("doc_id", "text"), cfg).filter("doc_id = component_id").select("doc_id").distinct()
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("d"))
    return rows.join(first, F.col("d.doc_id") == F.col("doc_id"), "left_semi").select("d.*")
