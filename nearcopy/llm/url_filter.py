"""URL filter: a cascade of Bloom filters that is exact on the corpus's own keys.

A rule is a host and a path prefix. Every url has a few candidate keys: each suffix of its host
at a dot, with each prefix of its path as long as some rule's path. The distinct candidate keys
of the corpus are the universe. Level 1 encodes the rules' keys; level 2 encodes the keys of the
universe that level 1 lets through wrongly; level 3 the rules' keys that level 2 holds wrongly, and
so on until a level has no wrong keys. On the universe the parity of the first level that
denies a key then says exactly whether it is listed, with no join at the time of use.

DataFrame functions only: filters are built by hash aggregates of 64-bit words and used as constant arrays.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from nearcopy.llm.common import check_columns, materialize

#: Bits for each key in level 1, and in the later ones; hash functions of either.
BITS, HASHES = (16, 4), (8, 2)
#: The largest level, in 64-bit words, that is put into the plan as a constant (8 MB).
MAX_WORDS = 1 << 20
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for a null url or one without ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^([^/?#]*)", 1), _UPPER, _LOWER)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1), F.lit(""))


def candidate_keys(host: Column, path: Column, lengths: list[int]) -> Column:
    """Array of candidate keys, longest first; of equal length the one with the longer host."""
    labels = F.split(host, "\\.", -1)
    suffixes = F.when(
        host != "",
        F.transform(
            F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), ".")
        ),
    ).otherwise(F.array().cast("array<string>"))
    prefixes = F.filter(
        F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in lengths]), lambda p: p.isNotNull()
    )
    pairs = F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.struct((-F.length(s) - F.length(p)).alias("a"), (-F.length(s)).alias("b"), F.concat(s, p).alias("key")))))
    return F.transform(F.array_sort(pairs), lambda x: x["key"])


def _positions(key: Column, level: int, words: int, hashes: int) -> list[Column]:
    return [F.pmod(F.xxhash64(key, F.lit(level), F.lit(h)), F.lit(words * 64)) for h in range(hashes)]


class BloomCascade:
    """levels: one (words, hashes) each; words are 64-bit integers."""

    def __init__(self, levels: list[tuple[list[int], int]]):
        self.levels = levels

    @staticmethod
    def fit(listed: DataFrame, universe: DataFrame, column: str = "key", max_levels: int = 64) -> BloomCascade:
        """listed: the keys to encode; universe: all distinct keys that will ever be asked.

        Wrong keys of a level are kept as DataFrames and never collected; the driver sees
        counts and the filters, whose size is checked. The wrong keys shrink by a constant
        factor a level, so a few levels do.
        """
        listed, levels = listed.select(column).where(F.col(column).isNotNull()).distinct(), []
        others = universe.select(column).distinct().join(listed, column, "left_anti")
        inside, outside, n = listed, others, listed.count()
        while n:
            if len(levels) == max_levels:
                raise RuntimeError("the cascade doesn't end; are there more hash functions than bits?")
            bits, hashes = BITS[bool(levels)], HASHES[bool(levels)]
            words = max(1, -(-n * bits // 64))
            if words > MAX_WORDS:
                raise ValueError(f"a level would take {words} words; split the list by a hash of its keys and fit one cascade for each part")
            spots = inside.select(
                F.explode(F.array(*_positions(F.col(column), len(levels), words, hashes))).alias("bit")
            )
            rows = spots.groupBy(F.shiftright("bit", 6).alias("word")).agg(
                F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("value")
            ).collect()
            filled = [0] * words
            for r in rows:
                filled[r["word"]] = r["value"]
            levels.append((filled, hashes))
            wrong = outside.where(BloomCascade._holds(F.col(column), len(levels) - 1, *levels[-1]))
            inside, outside = materialize(wrong), inside  # so the universe is read once
            n = inside.count()
        return BloomCascade(levels)

    @staticmethod
    def _holds(key: Column, level: int, words: list[int], hashes: int) -> Column:
        table = F.from_json(F.lit(json.dumps(words)), "array<bigint>")
        held = []
        for bit in _positions(key, level, len(words), hashes):
            word = F.element_at(table, (F.shiftright(bit, 6) + 1).cast("int"))
            held.append(F.getbit(word, F.pmod(bit, F.lit(64)).cast("int")) == 1)
        out = held[0]
        for h in held[1:]:
            out = out & h
        return out

    def contains(self, key: Column) -> Column:
        """Exact for the listed keys and every key of the universe; may err on others."""
        out = F.lit(len(self.levels) % 2 == 1)
        for level in reversed(range(len(self.levels))):
            out = F.when(self._holds(key, level, *self.levels[level]), out).otherwise(F.lit(level % 2 == 1))
        return out


def judge_urls(
    pages: DataFrame, rules: list[tuple[str, str, str]], url: str = "url", default: str = "allow"
) -> DataFrame:
    """Add host, path, rule and verdict to each row of `pages`.

    rules: (verdict, host, path). A rule fits its host and all subdomains if the path starts
    with the rule's path; the longest fitting rule wins (host and path counted together; then
    the longer host). No rule: `rule` is null and `verdict` is `default`. A null url and one without
    ``://`` have an empty host and path, and no rule. Repeated urls are judged one by one. Columns of
    `pages` with the names of the new ones are replaced. One cascade is fitted for each verdict. Of two
    equal rules the later counts.
    """
    check_columns(pages, url)
    spark = pages.sparkSession
    host, path = split_url(F.col(url))
    keys = {h.translate(str.maketrans(_UPPER, _LOWER)) + p: v for v, h, p in rules}
    lengths = sorted({len(p) for _, _, p in rules}, reverse=True)
    split = pages.withColumns({"host": host, "path": path})
    if not keys:
        return split.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    candidates = candidate_keys(F.col("host"), F.col("path"), lengths)
    universe = split.select("host", "path").distinct().select(F.explode(candidates).alias("key"))
    fitted = {}
    for verdict in sorted(set(keys.values())):
        listed = spark.createDataFrame([(k,) for k, v in keys.items() if v == verdict], "key string")
        fitted[verdict] = BloomCascade.fit(listed, universe)
    tests = {v: (lambda c: lambda k: c.contains(k))(c) for v, c in fitted.items()}

    def verdict_of(key: Column) -> Column:
        out = F.lit(None).cast("string")
        for v, test in tests.items():
            out = F.when(test(key), F.lit(v)).otherwise(out)
        return out

    found = F.get(
        F.filter(
            F.transform(candidates, lambda k: F.struct(k.alias("rule"), verdict_of(k).alias("verdict"))),
            lambda x: x["verdict"].isNotNull(),
        ),
        F.lit(0),
    )
    return split.withColumn("_hit", found).withColumns(
        {"rule": F.col("_hit.rule"), "verdict": F.coalesce(F.col("_hit.verdict"), F.lit(default))}
    ).drop("_hit")


RULES = [
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
]


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge_urls(pages, RULES).select("page_id", "host", "path", "rule", "verdict")


ORACLE_OP1 = """
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), split AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut
), rules(verdict, h, p) AS (
  VALUES ('allow', 'com', '/'), ('block', 'example.com', '/en/'), ('allow', 'www.example.com', '/en/'), ('block', 'net', '/es/'), ('block', 'net', '/fr/')
), fits AS (
  SELECT page_id, h || p AS rule, verdict,
         row_number() OVER (PARTITION BY page_id ORDER BY length(h) + length(p) DESC, length(h) DESC) AS k
  FROM split JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)
)
SELECT s.page_id, s.host, s.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM split s LEFT JOIN fits f ON s.page_id = f.page_id AND f.k = 1
"""
