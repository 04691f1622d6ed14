"""URL filters: a blocked Bloom filter in front of an exact hash join.

Canonical (host, path) rules go into a Bloom filter whose blocks are 64-bit
words.  For each URL the host suffixes and path prefixes of the shapes that
occur among the rules are tested against it; only possible hits are exploded
and joined exactly, so false positives vanish and most rows meet no join.
Built-in functions only.

Defined results: a null URL or one without ``://`` has empty host and path and
gets the default verdict; repeated rows stay; an empty rule list gives the
default to all; of rules that fit, the longest ``host + path`` wins, then the
longer host, then ``block``.  Other columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import ascii_lower

#: Largest filter that is put into a plan: 2**16 words are 512 KB.
MOST_WORDS = 1 << 16
#: Rules up to this count are broadcast for the exact join, else shuffled.
MOST_BROADCAST_RULES = 200_000
_BITS = 5


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL, as expressions."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr("substring({0}, instr({0}, '://') + 3)".format("`_url`")))
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)
    return ascii_lower(host), path


def _key(host: Column, path: Column) -> Column:
    return F.xxhash64(host, path)


def _block(key: Column, words: int) -> Column:
    return F.pmod(key, F.lit(words)).cast("int")


def _mask(key: Column) -> Column:
    out = None
    for i in range(_BITS):
        at = F.shiftrightunsigned(key, 20 + 6 * i).bitwiseAND(F.lit(63)).cast("int")
        bit = F.call_function("shiftleft", F.lit(1).cast("long"), at)
        out = bit if out is None else out.bitwiseOR(bit)
    return out


def build_filter(rules: DataFrame, n_rules: int, bits_per_key: int = 16) -> tuple[Column, int]:
    """The filter's words as an array expression, and their number (at most MOST_WORDS)."""
    words = 16
    while words * 64 < n_rules * bits_per_key and words < MOST_WORDS:
        words *= 2
    key = _key(F.col("host"), F.col("path"))
    rows = rules.groupBy(_block(key, words).alias("b")).agg(F.bit_or(_mask(key)).alias("m")).collect()  # at most `words` rows
    held = [0] * words
    for r in rows:
        held[r.b] = r.m
    return F.split(F.lit(",".join(map(str, held))), ",").cast("array<bigint>"), words


def url_filter(pages: DataFrame, rules: DataFrame, url: str = "url", keep: tuple[str, ...] = ("page_id",), default: str = "allow", bits_per_key: int = 16) -> DataFrame:
    """Judges every row of ``pages``.

    ``rules`` has host, path and verdict.  Returns ``keep`` plus host, path,
    rule (``host || path`` or null) and verdict.
    """
    rules = rules.select(ascii_lower(F.col("host")).alias("host"), F.col("path"), F.col("verdict")).where("host is not null and path is not null and verdict is not null")
    rules = rules.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))  # 'block' sorts after 'allow'
    shapes = [(r.l, r.p) for r in rules.select((F.length("host") - F.length(F.translate("host", ".", "")) + 1).alias("l"), F.length("path").alias("p")).distinct().collect()]
    base = pages.select(*keep, F.col(url).alias("_url"))
    host, path = split_url(F.col("_url"))
    base = base.select(*keep, host.alias("host"), path.alias("path"))
    if not shapes:
        return base.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    n_rules = rules.count()
    words, n_words = build_filter(rules, n_rules, bits_per_key)
    n_labels = F.length("host") - F.length(F.translate("host", ".", "")) + 1
    tests = F.from_json(F.lit("[" + ",".join(f'{{"l":{a},"p":{b}}}' for a, b in sorted(shapes)) + "]"), "array<struct<l:int,p:int>>")

    def candidate(s: Column) -> Column:
        return F.struct(
            F.call_function("substring_index", F.col("host"), F.lit("."), -s["l"]).alias("h"),
            F.call_function("substring", F.col("path"), F.lit(1), s["p"]).alias("p"),
        )

    def possible(c: Column) -> Column:
        key = _key(c["h"], c["p"])
        m = _mask(key)
        return F.element_at(words, _block(key, n_words) + 1).bitwiseAND(m) == m

    fits = F.filter(tests, lambda s: (n_labels >= s["l"]) & (F.length("path") >= s["p"]))
    found = F.filter(F.transform(fits, candidate), possible)
    hits = base.select("host", "path", F.explode(found).alias("c")).groupBy("host", "path", F.col("c.h").alias("h"), F.col("c.p").alias("p")).agg(F.lit(1).alias("one"))
    exact = rules.select(F.col("host").alias("h"), F.col("path").alias("p"), F.col("verdict").alias("_v"))
    exact = F.broadcast(exact) if n_rules <= MOST_BROADCAST_RULES else exact.hint("shuffle_hash")
    best = hits.join(exact, ["h", "p"]).groupBy("host", "path").agg(F.max(F.struct((F.length("h") + F.length("p")).alias("a"), F.length("h").alias("b"), F.concat("h", "p").alias("rule"), F.col("_v").alias("v"))).alias("x"))
    best = best.select(F.col("host").alias("_h"), F.col("path").alias("_p"), F.col("x.rule").alias("rule"), F.col("x.v").alias("_v"))
    out = base.join(best, (F.col("host") == F.col("_h")) & (F.col("path") == F.col("_p")), "left")
    return out.select(*keep, "host", "path", "rule", F.coalesce("_v", F.lit(default)).alias("verdict"))
