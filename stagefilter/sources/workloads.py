"""The fourteen keyed workloads: tables turned into rows (eid, h, is_key, split, x).

Keys are all in split `key`; non-keys are dealt to test, calib and train by their hash, so
the split is the same everywhere and at any time. Elements are distinct, and an identity
that occurs on both sides is a key.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stagefilter.functions.hashing import element_hash, uniform

LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def split_of(h: Column, is_key: Column) -> Column:
    v = F.pmod(h, F.lit(1000))
    return F.when(is_key, "key").when(v < 100, "test").when(v % 10 == 9, "calib").otherwise("train")


def keyed(rows: DataFrame, eid: Column, label: Column, features: list[Column], flip: float = 0.0) -> DataFrame:
    """Distinct elements with their labels (flipped for a share of them) and feature arrays. Elements without identity are left out."""
    x = F.array(*[F.coalesce(f.cast("float"), F.lit(float("nan")).cast("float")) for f in features])
    base = rows.select(eid.cast("string").alias("eid"), label.cast("boolean").alias("label"), x.alias("x")).filter("eid is not null and label is not null")
    if flip:
        base = base.withColumn("label", F.when(uniform("flip", F.col("eid")) < flip, ~F.col("label")).otherwise(F.col("label")))
    one = base.groupBy("eid").agg(F.max("label").alias("is_key"), F.max_by("x", F.struct("label", "x")).alias("x"))
    one = one.withColumn("h", element_hash(F.col("eid")))
    return one.select("eid", "h", "is_key", split_of(F.col("h"), F.col("is_key")).alias("split"), "x")


def line_features() -> list[Column]:
    q, p, d, t = F.col("l_quantity"), F.col("l_extendedprice"), F.col("l_discount"), F.col("l_tax")
    day = F.col("l_shipdate")
    return [
        q, p, d, t, F.col("l_linenumber"), F.col("l_partkey") % 97, F.col("l_suppkey") % 89, F.col("l_orderkey") % 101,
        p / F.greatest(q, F.lit(1.0)), p * d, p * (1 - d), p * (1 - d) * (1 + t), q * d, q * t, d * t, p / 1000 - q, p / 1000 + 200 * d, F.log1p(p), F.log1p(q),
        F.month(day), F.dayofweek(day), F.dayofyear(day), F.year(day), F.quarter(day), d - t, p * t, q * q, d * d,
    ]


def url_features(url: Column, html_len: Column | None = None) -> list[Column]:
    """Twenty lexical features of a URL."""
    n = F.length(url)
    count = lambda pattern: F.regexp_count(url, F.lit(pattern))
    host = F.coalesce(F.try_parse_url(url, F.lit("HOST")), F.lit(""))
    path = F.coalesce(F.try_parse_url(url, F.lit("PATH")), F.lit(""))
    query = F.coalesce(F.try_parse_url(url, F.lit("QUERY")), F.lit(""))
    ref = F.coalesce(F.try_parse_url(url, F.lit("REF")), F.lit(""))
    flag = lambda c: c.cast("int")
    return [
        n, count("[0-9]"), count("[^A-Za-z0-9]"), count("[.]"), count("/"), F.size(F.split(path, "/")), flag(url.startswith("https")), flag(count("[.]") > 2),
        flag(host.endswith(".com")), flag(host.endswith(".org")), flag(url.contains("/en/")), flag(url.contains(".html")), flag(url.endswith("/")), F.length(query), F.length(ref),
        count("[0-9]") / n, count("[aeiou]") / n, F.array_max(F.transform(F.split(url, "[^A-Za-z0-9]+"), lambda t: F.length(t))), F.size(F.array_distinct(F.split(url, ""))), F.size(F.split(url, "-")),
    ]


def text_features(text: Column, grams: int = 32) -> list[Column]:
    """Lengths, shares of character classes, counts of common letters and hashed word counts."""
    n = F.greatest(F.length(text), F.lit(1))
    drop = lambda chars: (F.length(text) - F.length(F.translate(text, chars, ""))) / n
    words = F.split(text, " ")
    # one pass over the words; a word adds to one of the buckets
    buckets = [F.size(F.filter(words, lambda w, i=i: F.pmod(F.crc32(w.cast("binary")), F.lit(grams)) == i)) / F.size(words) for i in range(grams)]
    return [n, F.size(words), n / F.size(words), F.size(F.array_distinct(words)) / F.size(words), *[drop(c) for c in "etaoinshrdluäöüßéèêçñóí.,!:\n"], drop("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), drop("0123456789"), *buckets]


def _vector(n: int = 64) -> list[Column]:
    return [F.get("embedding", F.lit(i)) for i in range(n)]


def _labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")


def _line(spark, sf_dir):
    return table(spark, sf_dir, "lineitem"), F.concat_ws("-", *LINE_KEY)


def physics_hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, eid = _line(spark, sf_dir)
    return keyed(rows, eid, F.col("l_extendedprice") / 1000 + 200 * F.col("l_discount") - F.col("l_quantity") > 36, line_features(), 0.25)


def null_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, eid = _line(spark, sf_dir)
    return keyed(rows, eid, F.col("l_returnflag") == "R", line_features())


def url_easy(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("url", F.explode(F.sequence(F.lit(0), F.lit(39))).alias("i"))
    return keyed(pages, F.concat("url", F.lit("/v"), F.col("i").cast("string")), F.col("url").rlike("[?#]"), url_features(F.col("url")), 0.05)


def file_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(_labelled(spark, sf_dir), F.sha2("text", 256), F.col("quality") == 0, text_features(F.col("text")))


def doc_toxic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(_labelled(spark, sf_dir), F.sha2("text", 256), F.col("toxic") == 1, text_features(F.col("text")))


def doc_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(table(spark, sf_dir, "documents"), F.sha2("text", 256), F.col("lang") != "en", text_features(F.col("text")))


def null_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(table(spark, sf_dir, "embeddings"), F.col("vec_id"), F.col("label") < 5, _vector())


def vec_linear(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _vector()
    return keyed(table(spark, sf_dir, "embeddings"), F.col("vec_id"), e[0] + e[1] - e[2] + e[3] > 0, e, 0.02)


def orders_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    day = F.col("o_orderdate")
    x = [F.col("o_totalprice"), F.year(day), F.month(day), F.dayofyear(day), F.substring("o_orderpriority", 1, 1), F.ascii("o_orderstatus"), F.col("o_custkey") % 97, F.unix_date(day.cast("date"))]
    return keyed(table(spark, sf_dir, "orders"), F.col("o_orderkey"), (F.col("o_totalprice") > 300000) | (day < F.lit("1996-06-01")), x, 0.1)


def cust_sep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return keyed(table(spark, sf_dir, "customer"), F.col("c_custkey"), F.col("c_acctbal") < 0, [F.col("c_acctbal"), F.col("c_nationkey"), F.ascii("c_mktsegment")])


def part_box(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = [F.col("p_retailprice"), F.col("p_size"), F.regexp_extract("p_brand", "([0-9]+)", 1), F.length("p_type"), F.length("p_name")]
    return keyed(table(spark, sf_dir, "part"), F.col("p_partkey"), (F.col("p_retailprice") > 950) & (F.col("p_size") < 30), x, 0.03)


def event_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    ts = F.col("ts")
    x = [F.col("value"), F.hour(ts), F.dayofweek(ts), F.col("user_id"), F.get_json_object("props", "$.k"), F.length("event_type")]
    return keyed(table(spark, sf_dir, "events"), F.col("event_id"), F.col("value") > 60, x, 0.1)


def turn_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.col("text")
    x = [F.length(t), F.size(F.split(t, " ")), F.regexp_count(t, F.lit("[.,!?]")), F.regexp_count(t, F.lit("\n")), F.col("turn") % 7]
    return keyed(table(spark, sf_dir, "conversations"), F.concat_ws("-", "conv_id", "turn"), F.col("role") == "assistant", x)


def ngram_bench(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """Eight-word shingles of documents; keys are those that a benchmark item has."""

    def shingles(name: str) -> DataFrame:
        w = table(spark, sf_dir, name).select(F.split("text", "\\s+").alias("w"))
        grams = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - n + 1, F.lit(1))), lambda i: F.array_join(F.slice("w", i, F.lit(n)), " "))
        return w.select(F.explode(grams).alias("g"))

    bench = shingles("benchmark").distinct().withColumn("hit", F.lit(True))
    rows = shingles("documents").distinct().join(bench, "g", "left")
    x = [F.length("g"), F.regexp_count("g", F.lit("[äöüßéèêñ]")), F.regexp_count("g", F.lit("[.,]")), F.regexp_count("g", F.lit("th")), F.regexp_count("g", F.lit("[A-Z]"))]
    return keyed(rows, F.col("g"), F.coalesce("hit", F.lit(False)), x)


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (url_easy, file_wide, physics_hard, null_rows, null_vec, vec_linear, orders_mix, cust_sep, part_box, event_tail, doc_lang, doc_toxic, turn_role, ngram_bench)
}


def load(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return WORKLOADS[name](spark, sf_dir)
