"""Operator 9: line-first quality rules, in DataFrame functions only.

Every line of a text is judged on its own (punctuation, navigation, boilerplate);
failing lines go, and a document that loses too much of its text that way is rejected.
Beside that verdict stand whole-document counts (words, symbols, repeated lines and
repeated five-word windows) with two hard limits. The lines that stay are the document's
new text, which is counted and judged by the two limits as a text of its own.

Edge cases: a null text counts as an empty one; an empty or blank text has no word and
fails the word minimum; lines without a word are neither kept nor lost; repeated rows
are judged one by one; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stagefilter.llm.common import OTHER_SPACE, let, without

SYMBOLS = "#*$%&|<>"
WINDOW = 5


@dataclass(frozen=True)
class LineRules:
    """Limits of the line rules. A line fails if one of them applies.

    short_words: a line without end punctuation fails if it has fewer words than this.
    shouting: share of exclamation and question marks to words over which a line fails.
    separators: number of menu separators from which a line counts as navigation.
    boilerplate: phrases (lower case) that mark a line as boilerplate, if the line is short.
    boilerplate_words: lines up to this length can be boilerplate.
    most_lost: share of a document's text that may go with failing lines.
    """

    short_words: int = 4
    shouting: float = 0.5
    separators: int = 3
    boilerplate: tuple[str, ...] = (
        "all rights reserved", "cookie policy", "enable javascript", "privacy policy", "terms of use", "terms of service",
        "subscribe to our", "click here", "lorem ipsum", "sign in to", "share this",
    )
    boilerplate_words: int = 30
    most_lost: float = 0.5
    least_words: int = 10
    most_repeated: float = 0.2


def has_any(text: Column, chars: str) -> Column:
    found = F.lit(False)
    for c in chars:
        found = found | F.contains(text, F.lit(c))
    return found


def spaced(text: Column) -> Column:
    """text with spaces for all white space. Character by character only where there is more of it than ends of lines."""
    return F.when(has_any(text, OTHER_SPACE.replace("\n", "")), F.translate(text, OTHER_SPACE, " " * len(OTHER_SPACE))).otherwise(F.replace(text, F.lit("\n"), F.lit(" ")))


def split_words(text: Column) -> Column:
    return F.array_remove(F.split(spaced(text), " "), "")


def line_fails(line: Column, rules: LineRules) -> Column:
    """Whether one line, blank-trimmed and with single kinds of space, fails a rule. Name a plain column: it is looked at often."""
    n_words = F.size(F.array_remove(F.split(line, " "), ""))
    ended = F.substring(line, -1, 1).isin(*".!?:;,…\"'”’»)]")
    marks = F.length(line) - F.length(without(line, "!?"))
    bars = F.when(has_any(line, "|»•>"), F.length(line) - F.length(without(line, "|»•>"))).otherwise(0)
    shouts = marks > n_words * rules.shouting
    if rules.shouting >= 0:  # then a line without marks need not be counted
        shouts = has_any(line, "!?") & shouts

    def boilerplate(low: Column) -> Column:
        phrase = F.lit(False)
        for p in rules.boilerplate:
            phrase = phrase | F.contains(low, F.lit(p))
        return phrase

    return (~ended & (n_words < rules.short_words)) | shouts | (bars >= rules.separators) | (let(F.lower(line), boilerplate) & (n_words <= rules.boilerplate_words))


def judged_lines(text: Column, rules: LineRules) -> Column:
    """The lines with a word, in order: the line as it stands, n, its characters without outer blanks, and whether it fails."""
    judged = F.transform(
        F.split(text, "\n"),
        lambda x: let(F.trim(spaced(x)), lambda t: F.struct(x.alias("line"), F.length(t).cast("long").alias("n"), ((F.length(t) > 0) & line_fails(t, rules)).alias("fails"))),
    )
    return F.filter(judged, lambda r: r.getField("n") > 0)


def passing(judged: Column) -> Column:
    return F.transform(F.filter(judged, lambda r: ~r.getField("fails")), lambda r: r.getField("line"))


def kept_lines(text: Column, rules: LineRules) -> Column:
    """The lines that pass, in order."""
    return passing(judged_lines(F.coalesce(text, F.lit("")), rules))


def repeated_window_words(tokens: Column) -> Column:
    """How many words lie in a window of five words that the array holds twice or more.

    Windows stand as 64-bit hashes, put together from those of words, pairs and fours. Where none repeats the answer is 0 at once; else the
    hashes are sorted with their places, places that have a neighbour of the same hash are
    kept, and the union of their windows is measured from the gaps between them.
    """
    pairs_of = lambda xs, step: F.zip_with(xs, F.slice(xs, 1 + step, F.greatest(F.size(xs) - step, F.lit(0))), lambda x, y: F.xxhash64(x, y))
    hashes = let(
        F.transform(tokens, lambda x: F.xxhash64(x)),
        lambda h: let(
            F.zip_with(pairs_of(pairs_of(h, 1), 2), F.slice(h, WINDOW, F.greatest(F.size(h) - WINDOW + 1, F.lit(0))), lambda x, y: F.xxhash64(x, y)),
            lambda five: F.slice(five, 1, F.greatest(F.size(h) - WINDOW + 1, F.lit(0))),  # what begins in the last four words is no window
        ),
    )

    def gaps(places: Column) -> Column:
        last = F.size(places) - 1
        width = F.transform(places, lambda p, i: F.when(i == last, F.lit(WINDOW)).otherwise(F.least(F.lit(WINDOW), F.get(places, i + 1) - p)))
        return F.aggregate(width, F.lit(0).cast("long"), lambda a, x: a + x)

    def twins(ordered: Column) -> Column:
        same = lambda x, other: F.coalesce(other.getField("h") == x.getField("h"), F.lit(False))
        places = F.transform(F.filter(ordered, lambda x, i: same(x, F.get(ordered, i - 1)) | same(x, F.get(ordered, i + 1))), lambda x: x.getField("i"))
        return let(F.array_sort(places), gaps)

    return let(
        hashes,
        lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(
            let(F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), twins)
        ),
    )


def base_fails(n_words: Column, n_repeat_words: Column, rules: LineRules) -> Column:
    return (n_words < rules.least_words) | (100 * n_repeat_words > 100 * rules.most_repeated * n_words)


def quality_rules(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """One row per document: base counts, base_failed, share of text lost with failing lines, kept; then what remains.

    rest is the text of the lines that pass, n_rest_words and n_rest_repeat_words are counted in it, rest_failed
    tells that it fails the two limits. kept does not ask for rest_failed; it is fixed by op9's SQL.
    """
    text = F.col("text")
    total = lambda xs: F.aggregate(xs, F.lit(0).cast("long"), lambda a, r: a + r.getField("n"))
    lines = let(
        judged_lines(text, rules),
        lambda xs: F.struct(
            (F.size(xs) - F.size(F.array_distinct(F.transform(xs, lambda r: r.getField("line"))))).cast("long").alias("dup"),
            total(xs).alias("all"),
            total(F.filter(xs, lambda r: r.getField("fails"))).alias("lost"),
            F.array_join(passing(xs), "\n").alias("rest"),
        ),
    )
    counts = lambda text: let(split_words(text), lambda w: F.struct(F.size(w).cast("long").alias("n"), repeated_window_words(w).alias("repeat")))
    counted = docs.select(F.col("doc_id"), F.coalesce(text, F.lit("")).alias("text")).select(
        "doc_id",
        counts(text).alias("words"),
        F.length(F.replace(spaced(text), F.lit(" "), F.lit(""))).cast("long").alias("word_chars"),
        (F.length("text") - F.length(without(text, SYMBOLS))).cast("long").alias("n_symbols"),
        lines.alias("lines"),
    )
    # a text that loses no line remains as it is counted
    counted = counted.withColumn("left", F.when(F.col("lines.lost") == 0, F.col("words")).otherwise(counts(F.col("lines.rest"))))
    failed = base_fails(F.col("words.n"), F.col("words.repeat"), rules)
    lost = F.coalesce(F.try_divide(F.col("lines.lost"), F.col("lines.all")), F.lit(0.0))
    return counted.select(
        "doc_id", F.col("words.n").alias("n_words"), "word_chars", "n_symbols", F.col("lines.dup").alias("n_dup_lines"), F.col("words.repeat").alias("n_repeat_words"),
        failed.alias("base_failed"), (~failed & (lost <= rules.most_lost)).alias("kept"), lost.alias("lost_share"),
        F.col("lines.rest").alias("rest"), F.col("left.n").alias("n_rest_words"), F.col("left.repeat").alias("n_rest_repeat_words"), base_fails(F.col("left.n"), F.col("left.repeat"), rules).alias("rest_failed"),
    )
