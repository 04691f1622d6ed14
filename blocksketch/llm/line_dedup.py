"""Line dedup by the number of distinct sites that show a line.

Every line is hashed; a HyperLogLog sketch of its sites is built per line hash
by each task and merged by aggregation.  Lines whose estimate is within the
sketch's error of the threshold get an exact distinct count.  A line on
``min_sites`` sites or more is boilerplate: it goes from every document, but
for its first occurrence (lowest doc_id, then position) when ``keep_first``.

Defined results: lines are compared after trimming; those under ``min_chars``
characters are never boilerplate; a null text stays null, and an empty one
empty; a null site counts as no site; rows repeated with their doc_id and text
are treated alike; other columns are carried through untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import discard, materialise

#: Line marks up to this number are broadcast, else joined by shuffle.
MOST_BROADCAST_LINES = 100_000
#: Parts into which each line's occurrences are dealt where marks are joined by shuffle.
SALTS = 16


def _hashes(line: Column) -> list[Column]:
    """Two independent 64-bit hashes: together the line's identity."""
    return [F.xxhash64(line).alias("h1"), F.xxhash64(F.lit("line"), line).alias("h2")]


def lines_of(documents: DataFrame, site: str, min_chars: int) -> DataFrame:
    """Hashes of all lines of ``min_chars`` or more: k (doc_id), t (text hash), pos, site, h1, h2."""
    flat = documents.select(F.col("doc_id").alias("k"), F.xxhash64("text").alias("t"), F.xxhash64(F.col(site)).alias("s"), F.col(site).isNotNull().alias("known"), F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    line = F.trim(F.regexp_replace("line", "^\\s+|\\s+$", ""))
    flat = flat.select("k", "t", F.when(F.col("known"), F.col("s")).alias("s"), "pos", line.alias("line")).where(F.length("line") >= min_chars)
    return flat.select("k", "t", "s", "pos", *_hashes(F.col("line")))


def site_spread(lines: DataFrame, min_sites: int, lg: int = 12) -> DataFrame:
    """(h1, h2, sites) of the lines on at least ``min_sites`` sites.

    ``sites`` is the sketch's estimate, or exact where the estimate is within
    three standard errors (and one site) of the threshold.
    """
    band = max(1.0, 3 * 1.04 / 2 ** (lg / 2) * min_sites)
    sketched = lines.where("s is not null").groupBy("h1", "h2").agg(F.hll_sketch_estimate(F.hll_sketch_agg("s", lg)).alias("sites"), F.count("*").alias("n"))
    # fewer occurrences than sites asked for decide without a look at the sketch
    sketched = materialise(sketched.where((F.col("n") >= min_sites) & (F.col("sites") >= min_sites - band)), "spread")
    near = sketched.where(F.col("sites") <= min_sites + band).select("h1", "h2")
    sure = sketched.where(F.col("sites") > min_sites + band).select("h1", "h2", F.col("sites").cast("long").alias("sites"))
    # every task first reduces its lines to distinct sites, so a hot line weighs its sites in each task
    pairs = _marked_lines(lines.where("s is not null"), near, near.count()).groupBy("h1", "h2", "s").agg(F.lit(1).alias("one"))
    return sure.unionByName(pairs.groupBy("h1", "h2").agg(F.count("*").alias("sites")).where(F.col("sites") >= min_sites))


def _marked_lines(lines: DataFrame, marks: DataFrame, n_marks: int) -> DataFrame:
    """The lines whose hashes are among ``marks``: a broadcast of a counted size, beyond it a salted shuffle join."""
    if n_marks <= MOST_BROADCAST_LINES:
        return lines.join(F.broadcast(marks), ["h1", "h2"])
    salted = marks.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return lines.withColumn("_salt", F.pmod(F.xxhash64("k", "t", "pos"), F.lit(SALTS)).cast("int")).join(salted, ["h1", "h2", "_salt"]).drop("_salt")


def boilerplate(documents: DataFrame, site: str = "source", min_sites: int = 10, min_chars: int = 15, keep_first: bool = True) -> DataFrame:
    """(k, t, gone): the line positions to remove from each document that has any."""
    lines = lines_of(documents, site, min_chars)
    marked = materialise(site_spread(lines, min_sites), "lines")
    n_marks = marked.count()
    found = _marked_lines(lines, marked.select("h1", "h2"), n_marks).select("k", "t", "pos", "h1", "h2")
    if keep_first:
        found = materialise(found, "found")
        discard(marked)
        first = found.groupBy("h1", "h2").agg(F.min(F.struct("k", "pos", "t")).alias("f")).select("h1", "h2", F.col("f.k").alias("fk"), F.col("f.pos").alias("fp"), F.col("f.t").alias("ft"))
        same = F.col("k").eqNullSafe(F.col("fk")) & (F.col("pos") == F.col("fp")) & (F.col("t") == F.col("ft"))
        found = _marked_lines(found, first, n_marks).where(~same)
    return found.groupBy("k", "t").agg(F.collect_set("pos").alias("gone"))


def _marked(documents: DataFrame, site: str, min_sites: int, min_chars: int, keep_first: bool) -> DataFrame:
    """_doc (all columns as one struct, so that no name can clash), _kept, _n_lines, _n_removed."""
    gone = boilerplate(documents, site, min_sites, min_chars, keep_first)
    base = documents.select(F.struct(*[F.col(f"`{c}`") for c in documents.columns]).alias("_doc"), F.col("doc_id").alias("_k"), F.xxhash64("text").alias("_t"), F.col("text").alias("_text"))
    held = gone.select(F.col("k").alias("_k2"), F.col("t").alias("_t2"), "gone")
    out = base.join(held, F.col("_k").eqNullSafe(F.col("_k2")) & (F.col("_t") == F.col("_t2")), "left")
    parts = F.split("_text", "\n", -1)
    left = F.filter(parts, lambda x, i: ~F.array_contains("gone", i))
    kept = F.when(F.col("gone").isNull(), F.col("_text")).otherwise(F.array_join(left, "\n"))
    n_lines = F.when(F.col("_text").isNull(), 0).otherwise(F.size(parts)).cast("long")
    return out.select("_doc", kept.alias("_kept"), n_lines.alias("_n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("_n_removed"))


def dedup_lines(documents: DataFrame, site: str = "source", min_sites: int = 10, min_chars: int = 15, keep_first: bool = True) -> DataFrame:
    """All rows and columns of ``documents`` plus ``_kept`` (text without boilerplate), ``_n_lines`` and ``_n_removed``.

    Columns of the input with one of these three names give way to them.
    """
    new = ["_kept", "_n_lines", "_n_removed"]
    return _marked(documents, site, min_sites, min_chars, keep_first).select(*[F.col(f"_doc.`{c}`") for c in documents.columns if c not in new], *new)


def without_boilerplate(documents: DataFrame, site: str = "source", min_sites: int = 10, min_chars: int = 15, keep_first: bool = True) -> DataFrame:
    """``documents`` with boilerplate lines gone from text (n_chars follows); rows left with no text at all go."""
    out = _marked(documents, site, min_sites, min_chars, keep_first).where("_n_removed = 0 or trim(_kept) <> ''")

    def column(c: str) -> Column:
        old = F.col(f"_doc.`{c}`")
        if c == "text":
            return F.col("_kept").alias(c)
        if c == "n_chars":
            return F.when(F.col("_n_removed") > 0, F.length("_kept").cast(documents.schema[c].dataType)).otherwise(old).alias(c)
        return old.alias(c)

    return out.select(*map(column, documents.columns))
