"""Operator 10: line dedup by a segment-partition edit join, in DataFrame functions only.

A line is a sequence of symbols: of characters if it is short, of words (what single spaces
separate) from `long` words on. Each has a threshold k: one edit per `per` symbols, `edits`
at least and `most` at most. Two lines are linked if their edit distance, counted in
symbols, is at most the threshold of the one with fewer symbols. Lines of `long` to
`long + most - 1` words are compared both ways, so that no pair falls between the two.

Two such lines share at least one of the k + 1 segments of the shorter one, at a place that
the edits can't have moved far. So each distinct line of n symbols is filed under its
segments (hash of n, segment number and content), and probes the files of the lengths
n - k .. n with the few runs of symbols that can match, chosen by the multi-match rule. The
places to look at are small constant tables by threshold, joined to every line by a generator. Keys
are shuffled once, texts never; lines that are repeated very often, of which there can only
be so many, are collapsed before. Only keys with two different lines, one of them filed, go
on, and only their lines' texts are fetched again.

Candidates are taken in two rounds, so that a family of near copies never becomes all its
pairs: neighbours in the list of each key first, by length, by text and by the text read
backwards; their verified links make components; then lists that still hold several
components are compared across these. Candidates must agree in all but so many of the
parities of their symbols' classes as the edits explain, and are verified by a banded bit-parallel edit
distance after common heads and tails are cut. Of each class the first line (least doc_id,
then text, then line number) stays and all others are removed.

Lines shorter than `least` characters are only compared for equality. Lines without a word
are never removed. Where its text is not needed a line stands as two hashes, of 64 and 32
bits, and only as the first in links.

Edge cases: null texts count as empty; empty and blank texts have no line to remove; very
long lines are lines like others; rows repeated with the same doc_id and text count once;
extra columns are ignored, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.llm.common import cut, let, release_finished_shuffles
from stagefilter.llm.components import components

#: Symbols fall into so many classes: one bit of a line's signature.
CLASSES = 126
BLANK = " \t\n\x0b\x0c\r"


@dataclass(frozen=True)
class LineJoin:
    """edits: least threshold; most: greatest one; per_chars, per_words: symbols per edit where the threshold grows, 0 where it is `edits` for all lines; long: words from which a line is compared by words, 0 for never; least: characters from which lines are compared by edits; broadcast_ids: most line ids that are broadcast to pick texts, more are joined by shuffling; often: most repeated lines that are collapsed before their keys are made, those with more than count / often occurrences."""

    edits: int = 1
    least: int = 20
    broadcast_ids: int = 2_000_000
    often: int = 500_000
    most: int = 0
    per_chars: int = 0
    per_words: int = 0
    long: int = 0

    @property
    def band(self) -> int:
        return max(self.edits, self.most)

    def threshold(self, n: Column, by_words: Column | bool) -> Column:
        """Threshold of a line of n symbols."""
        if not self.per_chars:
            return F.lit(self.edits)
        per = F.when(F.lit(by_words) if isinstance(by_words, bool) else by_words, self.per_words).otherwise(self.per_chars)
        return F.least(F.lit(self.band), F.greatest(F.lit(self.edits), F.floor(n / per))).cast("int")


#: The form of the registered queries.
GROWING = LineJoin(least=8, most=3, per_chars=25, per_words=20, long=20)


def has_word(line: Column) -> Column:
    return F.ltrim(line, F.lit(BLANK)) != ""


def occurrences(docs: DataFrame) -> DataFrame:
    """All lines: doc_id, version (hash of the text), line_no, line."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("version"), text.alias("text"))
    return rows.select("doc_id", "version", F.posexplode(F.split("text", "\n")).alias("line_no", "line"))


def symbols(line: Column, by_words: Column | bool) -> Column:
    if isinstance(by_words, bool):
        return F.split(line, " " if by_words else "")
    return F.when(by_words, F.split(line, " ")).otherwise(F.split(line, ""))


def signature(line: Column, by_words: Column | bool = False) -> Column:
    """Two words with a bit for each class: whether the line has an odd number of its symbols."""

    def odd(bits: Column, symbol: Column) -> Column:
        def flip(at: Column) -> Column:
            bit = F.call_function("shiftleft", F.lit(1).cast("long"), at % 63)
            return F.struct(F.when(at < 63, bits.getField("a").bitwiseXOR(bit)).otherwise(bits.getField("a")).alias("a"), F.when(at >= 63, bits.getField("b").bitwiseXOR(bit)).otherwise(bits.getField("b")).alias("b"))

        return let(F.pmod(F.hash(symbol), F.lit(CLASSES)), flip)

    none = F.struct(F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b"))
    return F.aggregate(symbols(line, by_words), none, odd)


def signatures_close(a: Column, b: Column, edits: int | Column) -> Column:
    """False only for lines more than `edits` apart: an edit flips two bits at most."""
    return F.bit_count(a.getField("a").bitwiseXOR(b.getField("a"))) + F.bit_count(a.getField("b").bitwiseXOR(b.getField("b"))) <= 2 * edits


def places(cfg: LineJoin) -> list[tuple[int, int, int, int, bool]]:
    """(threshold k, symbols that the filed line is shorter, segment, move, filed): where a line is filed and what it probes."""
    out = []
    for k in range(cfg.edits, cfg.band + 1):
        for shorter in range(k + 1):
            for i in range(1, k + 2):
                low, high = max(-(i - 1), shorter - (k + 1 - i)), min(i - 1, shorter + (k + 1 - i))
                # what is filed under a key also probes it: at equal length the only place is the segment's own
                out += [(k, shorter, i, move, shorter == 0 and move == 0) for move in range(low, high + 1)]
    return out


def _places_of(n: Column, by_words: Column, cfg: LineJoin) -> Column:
    """The places for a line of n symbols: of the thresholds that it or a filed line up to `band` symbols shorter can have."""
    low, high, out = cfg.threshold(n - cfg.band, by_words), cfg.threshold(n, by_words), None
    for a in range(cfg.edits, cfg.band + 1):
        for b in range(a, cfg.band + 1):
            some = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("s"), F.lit(i).alias("i"), F.lit(m).alias("m"), F.lit(f).alias("filed")) for k, s, i, m, f in places(cfg) if a <= k <= b])
            out = some if out is None else F.when((low == a) & (high == b), some).otherwise(out)
    return out


def line_keys(lines: DataFrame, cfg: LineJoin) -> DataFrame:
    """id, key, filed: what each line is filed under and what it probes. The lowest bit of a key says whether the line is compared by words there; these rows are most of what is shuffled, so they have no column for it."""
    n_words = F.octet_length("line") - F.octet_length(F.replace("line", F.lit(" "), F.lit(""))) + 1
    forms = F.array(F.lit(False)) if not cfg.long else F.when(F.col("n_words") < cfg.long, F.array(F.lit(False))).when(F.col("n_words") < cfg.long + cfg.band, F.array(F.lit(False), F.lit(True))).otherwise(F.array(F.lit(True)))
    each = lines.select("line", n_words.alias("n_words")).select("line", "n_words", F.explode(forms).alias("by_words"))
    n = F.when(F.col("by_words"), F.col("n_words")).otherwise(F.length("line"))
    # plain functions only: one with a lambda is interpreted, word by word
    cut_up = each.select(F.xxhash64("line").alias("id"), "by_words", "line", F.when(F.col("by_words"), F.split("line", " ")).alias("words"), n.alias("n"))
    at = cut_up.select("id", "by_words", "line", "words", "n", F.inline(_places_of(F.col("n"), F.col("by_words"), cfg))).withColumn("l", F.col("n") - F.col("s"))
    at = at.filter((F.col("l") > 0) & (cfg.threshold(F.col("l"), F.col("by_words")) == F.col("k")))
    # nearly even segments, the longer ones last
    even = F.floor(F.col("l") / (F.col("k") + 1)).cast("int")
    extra = F.col("l") - even * (F.col("k") + 1)
    start = 1 + even * (F.col("i") - 1) + F.greatest(F.lit(0), extra - (F.col("k") + 2 - F.col("i"))) + F.col("m")
    width = even + F.when(extra > F.col("k") + 1 - F.col("i"), 1).otherwise(0)
    at = at.select("id", "by_words", "line", "words", "n", "l", "i", "filed", start.alias("a"), width.alias("w")).filter((F.col("a") >= 1) & (F.col("a") + F.col("w") - 1 <= F.col("n")))
    run = lambda symbols: F.xxhash64("l", "i", symbols)
    content = F.when(F.col("by_words"), run(F.slice("words", F.col("a"), F.col("w")))).otherwise(run(F.substring("line", F.col("a"), F.col("w"))))
    return at.select("id", content.bitwiseAND(F.lit(-2).cast("long")).bitwiseOR(F.col("by_words").cast("long")).alias("key"), "filed")


def _without_common_ends(a: Column, b: Column) -> Column:
    """struct(a, b) of two arrays without their common head and tail, found by halving steps."""
    steps = F.array(*[F.lit(1 << k) for k in range(16, -1, -1)])
    rest = lambda x, k: F.slice(x, k + 1, F.size(x))
    start = lambda x, k: F.slice(x, F.lit(1), F.size(x) - k)

    def step(same, left):
        def one(s: Column, k: Column) -> Column:
            x, y = s.getField("a"), s.getField("b")
            ok = (F.size(x) >= k) & (F.size(y) >= k) & same(x, y, k)
            return F.struct(F.when(ok, left(x, k)).otherwise(x).alias("a"), F.when(ok, left(y, k)).otherwise(y).alias("b"))

        return one

    heads = step(lambda x, y, k: F.slice(x, F.lit(1), k) == F.slice(y, F.lit(1), k), rest)
    tails = step(lambda x, y, k: F.slice(x, -k, k) == F.slice(y, -k, k), start)
    return F.aggregate(steps, F.aggregate(steps, F.struct(a.alias("a"), b.alias("b")), heads), tails)


def within_edits(a: Column, b: Column, edits: int) -> Column:
    """Whether the edit distance of two texts is at most `edits`."""
    return within_band(symbols(a, False), symbols(b, False), edits, F.lit(edits))


def within_band(a: Column, b: Column, edits: int, k: Column) -> Column:
    """Whether the edit distance of two arrays is at most k <= `edits`, by bit vectors over a band of 2 * edits + 1 diagonals.

    Bit `top` of the vectors stands for the lowest diagonal of the band at the current
    column. While the band's end is inside the pattern the distance is carried along that
    diagonal, after that along the pattern's last row.
    """
    width = 2 * edits + 2
    top, ones = width - 1, (1 << width) - 1
    lit = lambda x: F.lit(x).cast("long")
    inv = lambda x: x.bitwiseXOR(lit(ones))
    bit = lambda x, at: F.call_function("shiftright", x, at).bitwiseAND(lit(1))

    def distance(s: Column) -> Column:
        p, t = s.getField("p"), s.getField("t")
        m = F.size(p)

        def step(state: Column, i: Column) -> Column:
            vp, vn = state.getField("vp"), state.getField("vn")
            hit = lit(0)
            for d in range(2 * edits + 1):
                hit = hit + F.when(F.get(p, i + (edits - d)) == F.get(t, i), lit(1 << (top - d))).otherwise(lit(0))

            def after(d0s: Column) -> Column:
                d0, seen = d0s.getField("d0"), d0s.getField("dist")
                hp = vn.bitwiseOR(inv(d0.bitwiseOR(vp)))
                hn = d0.bitwiseAND(vp)
                half = F.shiftright(d0, 1)
                past = i - (m - edits)
                inside = past < 0
                at = F.greatest(F.lit(0), top - 1 - past)
                along = bit(hp, at) - bit(hn, at)
                dist = seen + F.when(inside, 1 - bit(d0, F.lit(top))).otherwise(along)
                return F.struct(hn.bitwiseOR(inv(half.bitwiseOR(hp))).alias("vp"), half.bitwiseAND(hp).alias("vn"), dist.alias("dist"))

            d0 = (hit.bitwiseAND(vp) + vp).bitwiseXOR(vp).bitwiseOR(hit).bitwiseOR(vn).bitwiseAND(lit(ones))
            held = F.array(F.struct(d0.alias("d0"), state.getField("dist").alias("dist")))
            return F.element_at(F.transform(held, after), 1)

        start = F.struct(lit(ones - ((1 << (top - edits)) - 1)).alias("vp"), lit(0).alias("vn"), lit(edits).alias("dist"))
        return F.aggregate(F.sequence(F.lit(0), F.size(t) - 1), start, step).getField("dist")

    def judged(ends: Column) -> Column:
        x, y = ends.getField("a"), ends.getField("b")
        n, m = F.size(x), F.size(y)
        # the longer one is the pattern; it must outgrow the band, shorter ones differ by their length at most
        sides = F.struct(F.when(n >= m, x).otherwise(y).alias("p"), F.when(n >= m, y).otherwise(x).alias("t"))
        short = F.levenshtein(*[F.array_join(F.transform(z, lambda c: _place_of(c, F.concat(x, y))), "") for z in (x, y)])
        outcome = F.when(F.abs(n - m) > k, False).when(F.greatest(n, m) <= k, True).when(F.least(n, m) == 0, False)
        return outcome.when(F.greatest(n, m) <= edits, short <= k).otherwise(let(sides, distance) <= k)

    return let(_without_common_ends(a, b), judged)


def _place_of(symbol: Column, among: Column) -> Column:
    """A letter for the symbol: its first place in a short array."""
    return F.char(F.array_position(among, symbol) + 64)


def _met(lines: DataFrame, cfg: LineJoin) -> DataFrame:
    """id, by_words, key, filed where a key is filed and has two different lines."""
    by = Window.partitionBy("key")
    shared = line_keys(lines, cfg).select("*", F.min("id").over(by).alias("low"), F.max("id").over(by).alias("high"), F.max("filed").over(by).alias("some"))
    by_words = (F.col("key").bitwiseAND(F.lit(1).cast("long")) == 1).alias("by_words")
    return cut(shared.filter("low < high and some").select("id", by_words, "key", "filed").distinct())


def _texts(lines: DataFrame, met: DataFrame, cfg: LineJoin) -> DataFrame:
    """id, by_words, line, n, k, sig of the lines in `met`."""
    needed = cut(met.select("id", "by_words").distinct())
    if needed.count() <= cfg.broadcast_ids:
        needed = F.broadcast(needed)
    some = lines.withColumn("id", F.xxhash64("line")).join(needed, "id").select("id", "by_words", "line").distinct()
    some = some.withColumn("n", F.size(symbols(F.col("line"), F.col("by_words"))))
    return cut(some.select("id", "by_words", "line", "n", cfg.threshold(F.col("n"), F.col("by_words")).alias("k"), signature(F.col("line"), F.col("by_words")).alias("sig")))


def _fits(x: str, y: str) -> Column:
    k = F.least(f"{x}k", f"{y}k")
    return (F.abs(F.col(f"{x}n") - F.col(f"{y}n")) <= k) & signatures_close(F.col(f"{x}sig"), F.col(f"{y}sig"), k)


def _side(texts: DataFrame, name: str, *columns: str) -> DataFrame:
    return texts.select(F.col("id").alias(name), "by_words", *[F.col(c).alias(f"{name}_{c}") for c in columns])


def _verified(pairs: DataFrame, texts: DataFrame, cfg: LineJoin) -> DataFrame:
    """The pairs (a, b, by_words) of ids that are within their threshold."""
    both = pairs.join(_side(texts, "a", "line", "n", "k", "sig"), ["a", "by_words"]).join(_side(texts, "b", "line", "n", "k", "sig"), ["b", "by_words"]).filter(_fits("a_", "b_"))
    parts = [symbols(F.col(f"{c}_line"), F.col("by_words")) for c in "ab"]
    k = F.least("a_k", "b_k")
    near = F.lit(False)
    for edits in range(cfg.edits, cfg.band + 1):
        near = F.when(k == edits, within_band(*parts, edits, F.lit(edits))).otherwise(near)
    # dealt out anew: few keys may have most of the pairs
    return both.repartition("a", "b").filter(near).select("a", "b").distinct()


def _pair(x: str, y: str) -> list[Column]:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def _across(met: DataFrame, texts: DataFrame, near: DataFrame) -> DataFrame:
    """Pairs of lines that share a key, one of them filed, and stand in different components."""
    of = texts.select("id", "by_words", "n", "k", "sig").join(near, F.col("id") == F.col("node"), "left").select("id", "by_words", "n", "k", "sig", F.coalesce("component", "id").alias("c"))
    known = met.join(of, ["id", "by_words"])
    mixed = known.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.max("filed").alias("some")).filter("lo < hi and some").select("key")
    known = known.join(mixed, "key", "left_semi")
    x, y = (known.select("by_words", *[F.col(c).alias(f"{s}_{c}") for c in ("id", "key", "filed", "n", "k", "sig", "c")]) for s in "xy")
    on = (F.col("x_key") == F.col("y_key")) & F.col("x_filed") & (F.col("x_c") != F.col("y_c")) & _fits("x_", "y_")
    return x.join(y.drop("by_words"), on).select(*_pair("x_id", "y_id"), "by_words").distinct()


def line_links(lines: DataFrame, cfg: LineJoin = LineJoin()) -> DataFrame:
    """All pairs (a < b) of ids of different lines within their threshold. lines: column `line`, each at least cfg.least long; repeated lines are one."""
    met = _met(lines, cfg)
    texts = _texts(lines, met, cfg)
    alone = texts.select(F.col("id").alias("node"), F.col("id").alias("component")).distinct()
    return _verified(_across(met, texts, alone), texts, cfg)


def line_components(lines: DataFrame, cfg: LineJoin = LineJoin()) -> DataFrame:
    """(node, component) of the lines that are linked to others. Only links between components found so far are looked for."""
    met = _met(lines, cfg)
    release_finished_shuffles(lines.sparkSession)
    texts = _texts(lines, met, cfg)
    known = met.join(texts.select("id", "by_words", "n", F.left("line", F.lit(200)).alias("head"), F.reverse(F.right("line", F.lit(200))).alias("tail")), ["id", "by_words"])
    before = [F.lag("id").over(Window.partitionBy("key").orderBy(*order, "id")) for order in (["n"], ["head"], ["tail"])]
    chain = known.select("id", "by_words", F.array(*before).alias("before")).select("id", "by_words", F.explode("before").alias("before")).filter("before is not null")
    links = cut(_verified(chain.select(*_pair("id", "before"), "by_words").filter("a <> b").distinct(), texts, cfg))
    near = components(links)
    release_finished_shuffles(lines.sparkSession)
    late = cut(_verified(_across(met, texts, near), texts, cfg))
    found = components(links.union(late))
    return found.union(found.select("component", "component")).distinct()


def collapsed(rows: DataFrame, cfg: LineJoin) -> DataFrame:
    """The occurrences, but of each line that is repeated very often only the first. At most cfg.often such lines are broadcast."""
    here = F.struct("doc_id", "version", "line_no")
    named = rows.select(F.xxhash64("line").alias("id"), F.hash("line").alias("check"), here.alias("here"))
    counts = named.groupBy("id", "check").agg(F.count("*").alias("n"), F.min("here").alias("first"))
    counts = cut(counts.filter("n > 2"))
    # lines with three occurrences at least are counted among themselves: those above the limit are no more than cfg.often
    least = max(2, (counts.agg(F.sum("n")).first()[0] or 0) // cfg.often)
    often = F.broadcast(counts.filter(F.col("n") > least).select("id", "check", "first"))
    marked = rows.withColumn("id", F.xxhash64("line")).withColumn("check", F.hash("line")).join(often, ["id", "check"], "left")
    return marked.filter(F.col("first").isNull() | (F.col("first") == here)).select("doc_id", "version", "line_no", "line")


def line_classes(docs: DataFrame, cfg: LineJoin = LineJoin()) -> DataFrame:
    """One row per line with a word: doc_id, version, line_no, line_id, class_id, class_doc, removed.

    class_id is a line id of the class, class_doc the least doc_id that has a line of it.
    """
    rows = occurrences(docs).filter(has_word(F.col("line")))
    near = cut(line_components(collapsed(rows.filter(F.length("line") >= cfg.least), cfg), cfg))
    ids = rows.select("doc_id", "version", "line_no", F.xxhash64("line").alias("line_id"), F.hash("line").alias("check"))
    # linked lines are told by their class, others by both hashes
    known = ids.join(near, F.col("line_id") == F.col("node"), "left")
    known = known.select("doc_id", "version", "line_no", "line_id", F.coalesce("component", "line_id").alias("class_id"), F.when(F.col("node").isNull(), F.col("check")).otherwise(0).alias("check"))
    firsts = known.groupBy("class_id", "check").agg(F.min(F.struct("doc_id", "version", "line_no")).alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n")
    seen = known.join(firsts, ["class_id", "check"], "left")
    here = F.struct("doc_id", "version", "line_no")
    return seen.select("doc_id", "version", "line_no", "line_id", "class_id", F.coalesce("first.doc_id", "doc_id").alias("class_doc"), F.coalesce(F.col("first") != here, F.lit(False)).alias("removed"))


def without_repeated_lines(docs: DataFrame, cfg: LineJoin = LineJoin()) -> DataFrame:
    """All documents with the columns of docs, whatever their names; text without the removed lines, n_chars its length."""
    marks = line_classes(docs, cfg).filter("removed").groupBy("doc_id", "version").agg(F.sort_array(F.collect_set("line_no")).alias("gone"))
    # the documents' columns stay inside one struct, so that no name of theirs can clash
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("d"))
    text, version = F.col("d.text"), F.xxhash64(F.coalesce(F.col("d.text"), F.lit("")))
    joined = rows.join(marks, (F.col("d.doc_id").cast("long") == F.col("doc_id")) & (version == F.col("version")), "left").select("d", "gone")

    def without_gone(s: Column) -> Column:
        """The kept lines: gaps between the sorted numbers of removed ones are runs of them."""
        parts, edges = s.getField("parts"), s.getField("edges")
        run = lambda e, i: F.slice(parts, F.get(edges, i) + 2, e - F.get(edges, i) - 1)
        return F.array_join(F.flatten(F.transform(F.slice(edges, F.lit(2), F.size(edges) - 1), run)), "\n")

    lines = F.split(text, "\n")
    edges = F.concat(F.array(F.lit(-1)), F.col("gone"), F.array(F.size(lines)))
    kept = let(F.struct(lines.alias("parts"), edges.alias("edges")), without_gone)
    rebuilt = joined.select("d", "gone", F.when(F.col("gone").isNull(), text).otherwise(kept).alias("kept"))
    own = {"text": F.col("kept"), "n_chars": F.when(F.col("gone").isNull(), F.col("d.`n_chars`")).otherwise(F.length("kept"))} if "n_chars" in docs.columns else {"text": F.col("kept")}
    return rebuilt.select(*[own.get(c, F.col(f"d.`{c}`")).cast(docs.schema[c].dataType).alias(c) for c in docs.columns])
