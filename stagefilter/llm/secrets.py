"""Operator 3: secrets by patterns and by a randomness test battery, in DataFrame functions only.

Base spans come from three patterns (assignments, access key ids, hex runs). The method
adds long tokens that look random: for each candidate token an encoding is inferred, three
tests are run on its symbol codes (chi-squared uniformity over the encoding's alphabet,
runs about the alphabet's middle, serial correlation), their p-values are combined, and a
step-up false-discovery procedure inside each stratum of encoding and length band decides
which tokens are proven non-random. Of what it does not reject, so much is reported that the
estimated share of ordinary tokens among the reported stays within the same rate.

The false-discovery thresholds are taken from a histogram of all candidates of the
corpus: strata and bins are fixed in number, so the histogram is bounded and the
thresholds (one per stratum) are inlined as literals.

Positions are code points, ends exclusive. Edge cases: null text counts as empty; texts
without a match give zero counts and the digest of an empty string; repeated rows are
scanned each; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.llm.common import let

ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}+"
HEX = r"[0-9a-f]{32,}+"
KEYWORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")
#: Matches that are placed together; a text of many matches costs no more than blocks of so many and one step a block.
BLOCK = 256
KINDS = ("assign", "access", "hex", "random")

DIGITS, UPPER, LOWER = "0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Encodings in the order in which they are tried: pattern of the whole token, alphabet.
ENCODINGS = {
    "hex": (r"^(?:[0-9a-f]+|[0-9A-F]+)$", DIGITS + LOWER[:6]),
    "base32": (r"^[A-Z2-7]+$", UPPER + "234567"),
    "base36": (r"^(?:[0-9a-z]+|[0-9A-Z]+)$", DIGITS + LOWER),
    "base62": (r"^[0-9A-Za-z]+$", DIGITS + UPPER + LOWER),
    "base64": (r"^[0-9A-Za-z+/_-]+$", UPPER + LOWER + DIGITS + "+/"),
}


@dataclass(frozen=True)
class Battery:
    """least: shortest candidate; q: false-discovery rate; bins: bins of minus log p (four to a unit); bands: number of length bands, half an octave each."""

    least: int = 20
    q: float = 0.1
    bins: int = 200
    bands: int = 16


def _matches(text: Column, pattern: str, accept=None, group: int = 0) -> Column:
    """Start and end of each match that accept(group) takes; the places follow from the lengths between and of all matches."""

    def placed(found: Column) -> Column:
        def step(acc: Column, x: Column) -> Column:
            start = acc.getField("at") + x.getField("gap")
            end = start + x.getField("len")
            return F.struct(F.concat(acc.getField("out"), F.array(F.struct(start.alias("s"), end.alias("e"), x.getField("group").alias("t")))).alias("out"), end.alias("at"))

        gaps = F.split(text, pattern, -1)
        groups = F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
        parts = F.transform(F.arrays_zip(found.alias("m"), F.slice(gaps, F.lit(1), F.size(found)).alias("g"), groups.alias("t")), lambda z: F.struct(F.length(z.getField("g")).alias("gap"), F.length(z.getField("m")).alias("len"), z.getField("t").alias("group")))
        start = F.struct(F.array().cast("array<struct<s:int,e:int,t:string>>").alias("out"), F.lit(0).alias("at"))

        def joined(blocks: Column) -> Column:
            """Places in blocks of matches, each from its block's start; then the blocks are moved to theirs."""
            first = F.struct(F.array().cast("array<int>").alias("out"), F.lit(0).alias("at"))
            bases = F.aggregate(blocks, first, lambda acc, b: F.struct(F.concat(acc.getField("out"), F.array(acc.getField("at"))).alias("out"), (acc.getField("at") + b.getField("at")).alias("at"))).getField("out")
            moved = lambda b, base: F.transform(b.getField("out"), lambda x: F.struct((x.getField("s") + base).alias("s"), (x.getField("e") + base).alias("e"), x.getField("t").alias("t")))
            return F.flatten(F.zip_with(blocks, bases, moved))

        def in_blocks(all_: Column) -> Column:
            numbers = F.sequence(F.lit(0), F.floor((F.size(all_) - 1) / BLOCK).cast("int"))
            return let(F.transform(numbers, lambda b: F.aggregate(F.slice(all_, b * BLOCK + 1, BLOCK), start, step)), joined)

        spans = let(parts, in_blocks)
        return F.filter(spans, lambda x: accept(x.getField("t"))) if accept else spans

    empty = F.array().cast("array<struct<s:int,e:int,t:string>>")
    return let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda m: F.when(F.size(m) == 0, empty).otherwise(placed(m)))


def base_spans(text: Column) -> dict[str, Column]:
    low = F.lower(text)
    has = F.lit(False)
    for w in KEYWORDS:
        has = has | F.contains(low, F.lit(w))
    empty = F.array().cast("array<struct<s:int,e:int,t:string>>")
    return {
        "assign": F.when(has, _matches(text, ASSIGN, lambda t: F.length(t) >= 8, 1)).otherwise(empty),
        "access": F.when(F.contains(text, F.lit("AKIA")), _matches(text, ACCESS)).otherwise(empty),
        "hex": _matches(text, HEX),
    }


def _upper_tail(z: Column) -> Column:
    """Survival function of the standard normal, by the logistic cubic (error under 2e-4)."""
    return 1 / (1 + F.exp(F.greatest(F.least(1.5976 * z + 0.070565992 * z * z * z, F.lit(200.0)), F.lit(-200.0))))


def encoding_of(token: Column) -> Column:
    out = F.lit(None).cast("string")
    for name, (pattern, _) in reversed(ENCODINGS.items()):
        out = F.when(F.rlike(token, F.lit(pattern)), F.lit(name)).otherwise(out)
    return out


def _alphabet(encoding: Column) -> Column:
    out = F.lit(None).cast("string")
    for name, (_, alphabet) in ENCODINGS.items():
        out = F.when(encoding == name, F.lit(alphabet)).otherwise(out)
    return out


def battery_p(token: Column, encoding: Column) -> Column:
    """Combined p-value of the three tests under the hypothesis that the token is random in its encoding."""

    def tests(d: Column) -> Column:
        codes, k = d.getField("codes"), d.getField("k")
        n = F.size(codes).cast("double")
        add = lambda xs, f: F.aggregate(xs, F.lit(0.0), lambda a, x: a + f(x))
        squares = add(F.array_distinct(codes), lambda c: F.pow(F.size(F.filter(codes, lambda x: x == c)).cast("double"), F.lit(2.0)))
        chi = k * squares / n - n
        z1 = (chi - (k - 1)) / F.sqrt(2 * (k - 1) * (n - 1) / n)
        high = add(codes, lambda x: F.when(x >= k / 2, 1.0).otherwise(0.0))
        pairs = F.transform(F.slice(codes, F.lit(2), F.size(codes) - 1), lambda x, i: F.struct(F.get(codes, i).alias("a"), x.alias("b")))
        runs = 1 + add(pairs, lambda p: F.when((p.getField("a") >= k / 2) != (p.getField("b") >= k / 2), 1.0).otherwise(0.0))
        both = 2 * high * (n - high)
        z2 = F.try_divide(runs - both / n - 1, F.sqrt(F.greatest(both * (both - n) / (n * n * (n - 1)), F.lit(1e-9))))
        mean = add(codes, lambda x: x) / n
        spread = add(codes, lambda x: (x - mean) * (x - mean))
        r = F.coalesce(F.try_divide(add(pairs, lambda p: (p.getField("a") - mean) * (p.getField("b") - mean)), spread), F.lit(1.0))
        z3 = r * F.sqrt(n) + 1 / F.sqrt(n)
        floor = lambda p: F.greatest(p, F.lit(1e-30))
        half = -(F.log(floor(_upper_tail(z1))) + F.log(floor(F.least(F.lit(1.0), 2 * _upper_tail(F.abs(z2))))) + F.log(floor(F.least(F.lit(1.0), 2 * _upper_tail(F.abs(z3))))))
        return let(half, lambda h: F.exp(-h) * (1 + h + h * h / 2))

    alphabet = _alphabet(encoding)
    plain = F.when(encoding.isin("hex", "base36"), F.lower(token)).when(encoding == "base64", F.translate(token, "-_", "+/")).otherwise(token)
    codes = F.transform(F.split(plain, ""), lambda c: (F.instr(alphabet, c) - 1).cast("double"))
    return let(F.struct(codes.alias("codes"), F.length(alphabet).cast("double").alias("k")), tests)


def candidates(text: Column, cfg: Battery) -> Column:
    """Long tokens with letters and digits: place, stratum and bin of the combined p-value."""
    pattern = rf"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{{{cfg.least},}}+"
    mixed = lambda t: F.rlike(t, F.lit("[0-9]")) & F.rlike(t, F.lit("[A-Za-z]"))

    def judged(x: Column) -> Column:
        token = x.getField("t")
        band = F.least(F.floor(2 * F.log2(F.length(token) / F.lit(float(cfg.least)))), F.lit(cfg.bands - 1)).cast("int")
        return let(encoding_of(token), lambda enc: F.struct(x.getField("s").alias("s"), x.getField("e").alias("e"), F.concat_ws(":", enc, band.cast("string")).alias("stratum"), F.least(F.floor(-4 * F.log(F.greatest(battery_p(token, enc), F.lit(1e-30)))), F.lit(cfg.bins - 1)).cast("int").alias("bin")))

    return F.transform(_matches(text, pattern, mixed), judged)


def discovery_limits(cands: DataFrame, cfg: Battery) -> dict[str, int]:
    """By stratum the lowest bin that is not reported. cands has one column c, an array of candidates.

    Tokens that a step-up procedure at rate q proves non-random are not reported. Of the
    others only so many low p-values are that the share of non-random tokens among the
    reported stays within q by estimate: random tokens have even p-values, so their number
    follows from the tokens of the two highest bins (one more is counted, which lets sparse
    strata report), and what lies below in excess of it is taken for ordinary.
    """
    counts = cands.select(F.explode("c").alias("c")).groupBy("c.stratum", "c.bin").agg(F.count("*").alias("n"))
    whole, up = Window.partitionBy("stratum"), Window.partitionBy("stratum").orderBy("bin")
    ranked = counts.select(
        "stratum", "bin", F.sum("n").over(Window.partitionBy("stratum").orderBy(F.desc("bin"))).alias("rank"), F.sum("n").over(whole).alias("all"),
        F.sum("n").over(up).alias("reported"), F.coalesce(F.sum(F.when(F.col("bin") <= 1, F.col("n"))).over(whole), F.lit(0)).alias("head"),
    )
    proven = F.exp(-F.col("bin") / 4.0) <= cfg.q * F.col("rank") / F.col("all")
    random = (F.col("head") + 1) / F.lit(1 - math.exp(-0.5)) * (1 - F.exp(-(F.col("bin") + 1) / 4.0))
    fair = F.col("reported") - random <= cfg.q * F.col("reported")
    limits = ranked.groupBy("stratum").agg(F.least(F.coalesce(F.min(F.when(proven, F.col("bin"))), F.lit(cfg.bins)), F.coalesce(F.max(F.when(fair, F.col("bin"))) + 1, F.lit(0))).alias("bin"))
    return {r.stratum: r.bin for r in limits.collect()}


def find_secrets(docs: DataFrame, cfg: Battery = Battery()) -> DataFrame:
    """One row per document: counts of the base kinds, digest of the base spans, all spans."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select("doc_id", text.alias("text"))
    limits = discovery_limits(base.select(candidates(F.col("text"), cfg).alias("c")), cfg)
    found = base_spans(F.col("text"))
    spans = base.select("doc_id", *[v.alias(k) for k, v in found.items()], candidates(F.col("text"), cfg).alias("c"))
    placed = lambda xs, rank: F.transform(xs, lambda x: F.struct(x.getField("s").alias("s"), F.lit(rank).alias("k"), x.getField("e").alias("e")))
    listed = F.concat(*[placed(F.col(k), i) for i, k in enumerate(KINDS[:3])])
    if limits:
        table = F.create_map(*[x for k, v in sorted(limits.items()) for x in (F.lit(k), F.lit(v))])
        proven = lambda c: F.coalesce(F.element_at(table, c.getField("stratum")), F.lit(cfg.bins))
    else:
        proven = lambda c: F.lit(cfg.bins)
    with_base = spans.select("doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS[:3]], F.array_sort(listed).alias("base"), "c")
    fresh = F.filter("c", lambda c: (c.getField("bin") < proven(c)) & ~F.exists("base", lambda b: (b.getField("s") < c.getField("e")) & (c.getField("s") < b.getField("e"))))
    kind = lambda k: F.element_at(F.array(*map(F.lit, KINDS)), k + 1)
    said = lambda xs: F.array_join(F.transform(xs, lambda x: F.concat_ws(":", kind(x.getField("k")), x.getField("s").cast("string"), x.getField("e").cast("string"))), ",")
    return with_base.select(
        "doc_id", "n_assign", "n_access", "n_hex", F.sha2(said(F.col("base")), 256).alias("base_sha256"),
        said(F.array_sort(F.concat(F.col("base"), placed(fresh, 3)))).alias("spans"),
    )


__all__ = ["Battery", "battery_p", "candidates", "discovery_limits", "encoding_of", "find_secrets"]
