"""URL filter: a blocked Bloom filter in front of an exact join; DataFrame operations only.

A rule is a host and the begin of a path. It fits the host, its subdomains, and paths that begin so. The keys of a URL
are all pairs of a suffix of its host (at a dot) and a begin of its path that is as long as some rule's. Keys are looked
up in a blocked Bloom filter of the rules: one 64-bit word is chosen by the key's hash, and ``probes`` of its bits must
be set. Only keys that may be rules leave the row; an exact hash join with the rules removes the false ones, and the
longest rule wins (then the smaller one). URLs without any such key never take part in a shuffle.

The filter has a fixed number of words (``1 << log2_words``), so what travels with the plan has that bound whatever the
number of rules; a filter that is too small only lets more keys through to the join.

Nulls, empties, repeats: a null URL, or one without ``://``, has an empty host and path and no rule. Repeated rows each
come back. An empty table gives an empty result. Rules with a null host or path are ignored, repeated rules count once
(block wins over allow). All columns of the pages but clashing ones (host, path, rule, verdict) are kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    """The canonical host (lower case) and path of a URL."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"\A([^/?#]*)", 1), _UPPER, _LOWER)
    path = F.regexp_extract(rest, r"\A[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def rules_frame(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Rules given as (verdict, host, begin of path)."""
    return spark.createDataFrame(rules, "verdict string, host string, path string")


def _word(key: Column, log2_words: int) -> Column:
    return F.shiftrightunsigned(F.xxhash64(key), 64 - log2_words) if log2_words else F.lit(0).cast("long")


def _bits(key: Column, probes: int) -> Column:
    h = F.xxhash64(key, F.lit(1))
    mask = F.lit(0).cast("long")
    for k in range(probes):
        mask = mask.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftright(h, 6 * k).bitwiseAND(F.lit(63)).cast("int")))
    return mask


def bloom(rules: DataFrame, log2_words: int, probes: int) -> DataFrame:
    """One row with ``words``: the filter as a map from word number to bits, without the empty words."""
    words = rules.select(_word(F.col("key"), log2_words).alias("w"), _bits(F.col("key"), probes).alias("b")).groupBy("w").agg(F.bit_or("b").alias("b"))
    return words.agg(F.map_from_entries(F.collect_list(F.struct("w", "b"))).alias("words"))


def judge(pages: DataFrame, rules: DataFrame, url_col: str = "url", default: str = "allow", log2_words: int = 12, probes: int = 4) -> DataFrame:
    """``pages`` with ``host``, ``path``, ``rule`` (the host and path that won, or null) and ``verdict``."""
    sep = F.lit("\t")
    rules = rules.where("host is not null and path is not null and verdict is not null").groupBy(F.translate("host", _UPPER, _LOWER).alias("host"), "path").agg(F.max("verdict").alias("verdict"))
    rules = rules.withColumn("key", F.concat("host", sep, "path"))
    lengths = sorted(r[0] for r in rules.select(F.length("path")).distinct().limit(4097).collect())
    if len(lengths) > 4096:
        raise ValueError("more than 4096 different lengths of rule paths")
    words = bloom(rules, log2_words, probes).first()["words"] or {}
    base = pages.drop("host", "path", "rule", "verdict")
    host, path = host_and_path(F.col(url_col))
    base = base.withColumn("host", host).withColumn("path", path)
    if not words:
        return base.withColumn("rule", F.lit(None).cast("string")).withColumn("verdict", F.lit(default))
    # The filter as one array that holds the words in their order; 0 where no rule falls.
    filled = F.lit(b"".join((words.get(w, 0) & (1 << 64) - 1).to_bytes(8, "big") for w in range(1 << log2_words)))
    parts = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, k, F.size(parts)), "."))
    begins = F.array_compact(F.array(*[F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in lengths]))
    keys = F.flatten(F.transform(suffixes, lambda s: F.transform(begins, lambda p: F.concat(s, sep, p))))

    def may_be(key: Column) -> Column:
        word = F.conv(F.hex(F.substring(filled, _word(key, log2_words).cast("int") * 8 + 1, F.lit(8))), 16, -10).cast("long")
        mask = _bits(key, probes)
        return word.bitwiseAND(mask) == mask

    probed = base.withColumn("__keys", F.when(F.col("host") != "", F.filter(keys, may_be)).otherwise(F.array().cast("array<string>")))
    hits = probed.where(F.size("__keys") > 0)
    urls = hits.select("host", "path", "__keys").groupBy("host", "path").agg(F.first("__keys").alias("keys"))
    won = urls.select("host", "path", F.explode("keys").alias("key")).join(rules.select("key", F.concat("host", "path").alias("rule"), "verdict"), "key")
    best = won.groupBy(F.col("host").alias("__h"), F.col("path").alias("__p")).agg(F.min_by(F.struct("rule", "verdict"), F.struct(-F.length("rule"), "rule")).alias("best"))
    told = hits.join(best, (F.col("host") == F.col("__h")) & (F.col("path") == F.col("__p")), "left")
    out = [c for c in base.columns]
    told = told.select(*out, F.col("best.rule").alias("rule"), F.coalesce(F.col("best.verdict"), F.lit(default)).alias("verdict"))
    clear = probed.where(F.size("__keys") == 0).select(*out, F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    return told.unionByName(clear)
