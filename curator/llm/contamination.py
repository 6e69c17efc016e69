"""Benchmark contamination by winnowed fingerprints, in DataFrame functions only.

Of every ``window`` consecutive words the smallest hash among their short grams is the fingerprint, in documents
and items alike, so a shared window always shares one.  Documents' fingerprints meet the items' in a join; a hit
is then extended: the windows around it are compared word by word with the items' windows.

Candidates are found with words in Unicode lower case (a wider relation, cheap in the JVM); windows are confirmed
with A-Z lowered only.  Items shorter than a window are one window of their own length and are looked up directly.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from curator.functions.joins import small
from curator.functions.workspace import release, stash
from curator.llm.rows import keyed, per_row

WINDOW_WORDS = 13
#: Words of a short gram.
GRAM = 5
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A word once A-Z are lowered, and the same words before that.
_WORD_LOWERED = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_WORD_AS_IS = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def _words_as_is(text: Column) -> Column:
    return F.coalesce(F.regexp_extract_all(text, F.lit(_WORD_AS_IS), F.lit(0)), F.array().cast("array<string>"))


def _gram(h: Column, i: Column, k: int) -> Column:
    return F.xxhash64(F.lit(k), *[F.get(h, i + j) for j in range(k)])


def _with_hashes(df: DataFrame) -> DataFrame:
    """Adds h (word hashes) and g (gram hashes, one for each place where a gram starts)."""
    df = df.withColumn("h", F.transform("words", lambda w: F.xxhash64(F.lower(w))))
    h = F.col("h")
    starts = F.slice(h, F.lit(1), F.greatest(F.size(h) - (GRAM - 1), F.lit(0)))
    return df.withColumn("g", F.transform(starts, lambda _, i: _gram(h, i, GRAM)))


def _least(g: Column, size: int) -> Column:
    """Fingerprint of the window that starts at each place."""
    width = size - GRAM + 1
    starts = F.slice(g, F.lit(1), F.greatest(F.size(g) - (width - 1), F.lit(0)))
    return F.transform(starts, lambda _, i: F.array_min(F.slice(g, i + 1, F.lit(width))))


def _short(h: Column, size: int) -> Column:
    """Hashes of all runs of ``size`` words, for items of that length."""
    starts = F.slice(h, F.lit(1), F.greatest(F.size(h) - (size - 1), F.lit(0)))
    return F.transform(starts, lambda _, i: _gram(F.col("h"), i, size))


def _item_windows(items: DataFrame, size: int) -> DataFrame:
    """(item, n, at, window, print): every window of every item that has words."""
    lowered = F.translate(F.col("text").cast("string"), _UPPER, _LOWER)
    base = items.select(F.col("item_id").cast("string").alias("item"), F.regexp_extract_all(lowered, F.lit(_WORD_LOWERED), F.lit(0)).alias("words")).where(F.size("words") > 0)
    base = _with_hashes(base)
    long = base.where(F.size("words") >= size).select("item", "words", F.posexplode(_least(F.col("g"), size)).alias("at", "print"))
    long = long.select("item", F.lit(size).alias("n"), F.array_join(F.slice("words", F.col("at") + 1, F.lit(size)), " ").alias("window"), "print")
    out = long
    for n in range(1, size):
        out = out.unionAll(base.where(F.size("words") == n).select("item", F.lit(n).alias("n"), F.array_join("words", " ").alias("window"), _gram(F.col("h"), F.lit(0), n).alias("print")))
    return out.distinct()


def _hit_places(marks: Column, n: int) -> Column:
    """(at, n) of the places of a mark that is among the text's hits."""
    numbered = F.transform(marks, lambda m, i: F.struct(i.alias("at"), m.alias("m")))
    return F.transform(F.filter(numbered, lambda s: F.array_contains("hits", s["m"])), lambda s: F.struct(s["at"].alias("at"), F.lit(n).alias("n")))


def contaminated_words(docs: DataFrame, items: DataFrame, size: int = WINDOW_WORDS) -> DataFrame:
    """(key, text) and (item_id, text) -> (key, n_words, n_hit, n_items, items_sha256)."""
    if size < GRAM:
        raise ValueError(f"windows have {GRAM} words or more")
    windows = stash(_item_windows(items, size), "items")
    lengths = sorted(r[0] for r in windows.select("n").distinct().collect())  # at most ``size`` numbers
    prints = stash(windows.select("print").distinct(), "prints")

    hashed = _with_hashes(docs.select("key", _words_as_is(F.col("text")).alias("words")))
    marks = {n: _least(F.col("g"), size) if n == size else _short(F.col("h"), n) for n in lengths}
    lists = F.array_distinct(F.concat(*marks.values())) if marks else F.array().cast("array<bigint>")
    exploded = hashed.select("key", F.size("words").cast("long").alias("n_words"), F.explode_outer(lists).alias("print"))
    met = exploded.join(small(prints.withColumn("hit", F.col("print")), 40), "print", "left")
    found = stash(met.groupBy("key").agg(F.first("n_words").alias("n_words"), F.collect_set("hit").alias("hits")), "hits")

    near = found.where(F.size("hits") > 0).select("key", "hits")
    near = stash(near, "near")
    again = _with_hashes(docs.join(small(near, 200), "key").select("key", "hits", _words_as_is(F.col("text")).alias("words")))
    places = [_hit_places(marks[n], n) for n in lengths]
    if not places:
        places = [F.array().cast("array<struct<at:int,n:int>>")]
    spots = again.select("key", "words", F.explode(F.concat(*places)).alias("p"))
    spots = spots.select("key", F.col("p.at").alias("at"), F.col("p.n").alias("n"), F.translate(F.array_join(F.slice("words", F.col("p.at") + 1, F.col("p.n")), " "), _UPPER, _LOWER).alias("window"))
    sure = spots.join(small(windows.select("window", "n", "item"), 400), ["window", "n"])
    spans = sure.groupBy("key").agg(F.array_sort(F.collect_set(F.struct(F.col("at").alias("b"), (F.col("at") + F.col("n")).alias("e")))).alias("spans"), F.array_sort(F.collect_set("item")).alias("items"))
    covered = F.aggregate(
        "spans",
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("e")),
        lambda acc, s: F.struct((acc["n"] + F.greatest(s["e"] - F.greatest(acc["e"], s["b"]), F.lit(0))).alias("n"), F.greatest(acc["e"], s["e"]).alias("e")),
        lambda acc: acc["n"],
    )
    spans = stash(spans.select("key", covered.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256")), "spans")
    for used in (windows, prints, near):
        release(used)
    return found.select("key", "n_words").join(spans, "key", "left").select(
        "key", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"), F.coalesce("items_sha256", F.sha2(F.lit(""), 256)).alias("items_sha256")
    )


def contamination(docs: DataFrame, items: DataFrame, size: int = WINDOW_WORDS) -> DataFrame:
    """documents, benchmark -> (doc_id, n_words, n_hit, n_items, items_sha256, contaminated) for every row.

    Words are runs of letters, digits and non-ASCII characters.  Null and blank texts have no words and are not
    contaminated; items without words have no window; an item without an id marks words but is not counted.
    Rows that repeat an id and its text share one result.
    """
    base, rows = keyed(docs)
    out = per_row(contaminated_words(base, items, size), rows)
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))
