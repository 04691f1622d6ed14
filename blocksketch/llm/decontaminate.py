"""Benchmark decontamination with a broadcast set of normalised n-grams.

Benchmark items become windows of ``n`` words (an item of fewer words is one
window).  Two literal sets travel with the plan: hashes of the windows' first
words, which skip most positions, and the windows themselves, which decide
exactly.  The scan of a document is a chain of built-in array functions; only
the found windows are exploded, to look up the items that hold them.  The sets
grow with the benchmark, so their size is checked: beyond ``MOST_WINDOWS``
windows the documents' windows are joined by shuffle instead.

Defined results: a null or wordless text has no words and is never hit; a null
benchmark text has no windows; an item without an id hits words like any other
but is in no list of items; repeated document rows are each reported; an empty
benchmark hits nothing.  Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import ascii_lower, materialise

#: Fixed by the contract: what counts as a word after lower-casing A-Z.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Windows that may travel as literals (about 100 bytes each).
MOST_WINDOWS = 200_000


def words_of(text: Column) -> Column:
    """The text's words; null has none."""
    return F.regexp_extract_all(ascii_lower(F.coalesce(text, F.lit(""))), F.lit(WORD), F.lit(0))


def benchmark_windows(benchmark: DataFrame, n: int = 13, item: str = "item_id", text: str = "text") -> DataFrame:
    """One row per distinct window: gram, length in words, sorted item ids as strings."""
    w = benchmark.select(F.col(item).cast("string").alias("item"), words_of(F.col(text)).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - n + 1, F.lit(1)))
    grams = w.select("item", F.explode(F.transform(starts, lambda i: F.slice("w", i, n))).alias("g"))
    return grams.groupBy(F.array_join("g", " ").alias("gram"), F.size("g").alias("len")).agg(F.sort_array(F.collect_set("item")).alias("items"))


def _head(w: Column, i: Column, k: int) -> Column:
    return F.xxhash64(*[F.get(w, i + j) for j in range(k)])


def _quoted(values: list[str]) -> Column:
    return F.from_json(F.lit("[" + ",".join(values) + "]"), "array<string>")


def scan(documents: DataFrame, windows: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", n: int = 13) -> DataFrame:
    """``keep`` plus w (number of words), hits: array of (s, e, gram) of found windows in order."""
    n_windows = windows.count()
    docs = documents.select(*keep, words_of(F.col(text)).alias("w"))
    kind = "array<struct<s:int,e:int,gram:string>>"
    if n_windows == 0:
        return docs.select(*keep, F.size("w").alias("n_words"), F.array().cast(kind).alias("hits"))
    if n_windows > MOST_WINDOWS:
        return _scan_by_join(documents, windows, keep, text)
    held = windows.select("gram", "len").collect()  # bounded by MOST_WINDOWS
    by_len: dict[int, list[str]] = {}
    for r in held:
        by_len.setdefault(r.len, []).append(r.gram)
    found = []
    for m, grams in sorted(by_len.items()):
        k = min(3, m)
        heads = windows.where(F.col("len") == m).select(F.split("gram", " ").alias("w")).select(_head(F.col("w"), F.lit(0), k).alias("h")).distinct().collect()
        heads = [r.h for r in heads]

        def here(w: Column, m: int = m, k: int = k, heads: list[int] = heads, grams: list[str] = grams) -> Column:
            starts = F.filter(F.sequence(F.lit(0), F.size(w) - m), lambda i: _head(w, i, k).isin(heads))
            spans = F.transform(starts, lambda i: F.struct(i.cast("int").alias("s"), (i + m).cast("int").alias("e"), F.array_join(F.slice(w, i + 1, m), " ").alias("gram")))
            exact = F.filter(spans, lambda x: x["gram"].isin(grams))
            return F.when(F.size(w) >= m, exact).otherwise(F.array().cast(kind))

        found.append(here)
    hits = F.transform(F.array("w"), lambda w: F.struct(F.size(w).alias("n"), F.concat(*[f(w) for f in found]).alias("h")))
    out = docs.select(*keep, F.element_at(hits, 1).alias("x"))
    return out.select(*keep, F.col("x.n").alias("n_words"), (F.col("x.h") if len(found) == 1 else F.array_sort("x.h")).alias("hits"))


def _scan_by_join(documents: DataFrame, windows: DataFrame, keep: tuple[str, ...], text: str) -> DataFrame:
    """The way beyond MOST_WINDOWS: hashes of the document windows meet those of the set by a shuffle join.

    Only row number, place and hash of a window are shuffled.  The places found
    come back to their stored row, where the words themselves decide.
    """
    kind = "array<struct<s:int,e:int,gram:string>>"
    rows = documents.select(F.monotonically_increasing_id().alias("_row"), F.struct(*[F.col(f"`{c}`").alias(f"k{i}") for i, c in enumerate(keep)]).alias("_keep"), words_of(F.col(text)).alias("w"))
    rows = materialise(rows, "words")  # fixes the row numbers
    lengths = [r.len for r in windows.select("len").distinct().collect()]  # at most n
    gram = lambda s, e: F.array_join(F.slice("w", s + 1, e - s), " ")

    def places(m: int) -> Column:
        starts = F.when(F.size("w") >= m, F.sequence(F.lit(0), F.size("w") - m)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.struct(i.cast("int").alias("s"), (i + m).cast("int").alias("e"), F.xxhash64(gram(i, i + m)).alias("h")))

    flat = rows.select("_row", F.explode(F.concat(*[places(m) for m in lengths])).alias("x")).select("_row", "x.s", "x.e", "x.h")
    known = windows.select(F.xxhash64("gram").alias("h"), "gram")
    found = flat.join(known, "h").groupBy("_row").agg(F.array_sort(F.collect_list(F.struct("s", "e", "gram"))).alias("found"))
    out = rows.join(found, "_row", "left")
    hits = F.filter(F.coalesce("found", F.array().cast(kind)), lambda x: gram(x["s"], x["e"]) == x["gram"])
    return out.select(*[F.col(f"_keep.k{i}").alias(c) for i, c in enumerate(keep)], F.size("w").alias("n_words"), hits.cast(kind).alias("hits"))


def covered(hits: Column) -> Column:
    """Words covered by the union of the sorted spans."""
    zero = F.struct(F.lit(0).cast("int").alias("e"), F.lit(0).cast("long").alias("t"))
    step = lambda a, x: F.struct(F.greatest(a["e"], x["e"]).alias("e"), (a["t"] + F.greatest(F.lit(0), x["e"] - F.greatest(a["e"], x["s"]))).cast("long").alias("t"))
    return F.aggregate(hits, zero, step, lambda a: a["t"])


def decontaminate(documents: DataFrame, benchmark: DataFrame, keep: tuple[str, ...] = ("doc_id",), n: int = 13, least_share: float = 0.05) -> DataFrame:
    """Reports every document row: ``keep``, n_words, n_hit, items, spans, contaminated.

    ``spans`` are the found (start, end) word ranges; ``contaminated`` is
    n_hit > 0 and n_hit >= least_share * n_words.
    """
    windows = benchmark_windows(benchmark, n)
    found = scan(documents, windows, keep, n=n).withColumn("_row", F.monotonically_increasing_id())
    found = found.select(*keep, "_row", F.col("n_words").cast("long").alias("n_words"), covered(F.col("hits")).alias("n_hit"), F.transform("hits", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))).alias("spans"), F.array_distinct(F.transform("hits", lambda x: x["gram"])).alias("grams"))
    flat = found.select(*keep, "_row", "n_words", "n_hit", "spans", F.explode_outer("grams").alias("gram"))
    small = windows.select("gram", "items")
    flat = flat.join(F.broadcast(small) if small.count() <= MOST_WINDOWS else small, "gram", "left")
    out = flat.groupBy("_row").agg(*[F.first(k).alias(k) for k in (*keep, "n_words", "n_hit", "spans")], F.sort_array(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    share = round(1 / least_share)
    return out.select(*keep, "n_words", "n_hit", "items", "spans", ((F.col("n_hit") > 0) & (F.col("n_hit") * share >= F.col("n_words"))).alias("contaminated"))


def clean_documents(documents: DataFrame, benchmark: DataFrame, n: int = 13, least_share: float = 0.05) -> DataFrame:
    """The documents that are not contaminated, with all their columns and whole texts."""
    names = documents.columns
    windows = benchmark_windows(benchmark, n)
    packed = documents.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_doc"), F.col("text").alias("text"))
    found = scan(packed, windows, ("_doc",), n=n)
    share = round(1 / least_share)
    hit = covered(F.col("hits"))
    return found.where(~((hit > 0) & (hit * share >= F.col("n_words")))).select("_doc.*")
