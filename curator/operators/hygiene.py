"""Before any geometry: benchmark items and copies leave the corpus."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from curator.functions.graph import components
from curator.functions.joins import small, spread
from curator.functions.text import WORD, words
from curator.functions.workspace import release, stash


def _grams(lowered: Column, n: int) -> Column:
    """Distinct hashes of the n-word grams of a text in lower case, a shorter text being one gram; null without words.

    The word hashes are bound by a lambda, so they are made once a text wherever the optimiser moves this expression:
    named by a column, they would be made again for each gram in the filter that it infers below an ``explode``.
    """
    hashes = F.transform(words(lowered), lambda w: F.xxhash64(w))
    starts = lambda h: F.sequence(F.lit(0), F.greatest(F.size(h) - n, F.lit(0)))
    each = lambda h: F.transform(starts(h), lambda i: F.xxhash64(F.slice(h, i + 1, F.lit(n))))
    return F.transform(F.array(hashes), lambda h: F.when(F.size(h) > 0, F.array_distinct(each(h))))[0]


def _gram_sets(df: DataFrame, key: str, n: int) -> DataFrame:
    """(key, grams): distinct hashes of the n-word grams of a text; a shorter text is one gram."""
    return df.where(F.col("text").rlike(WORD)).select(key, _grams(F.lower("text"), n).alias("grams"))


def _gram_hashes(df: DataFrame, key: str, n: int, lowered: bool = False) -> DataFrame:
    """(key, g): a row for each distinct gram.  ``lowered``: the texts are in lower case."""
    return df.select(key, F.explode(_grams(F.col("text") if lowered else F.lower("text"), n)).alias("g"))


#: Bytes of text that are marked at once.
SLICE = 1 << 20
#: So many marks are held by each task at most; texts are not sifted by more.
MARKS = 1 << 19
_RANDOM = np.random.default_rng(7)
_BYTES, _BASE = _RANDOM.integers(1, 1 << 63, 256).astype(np.uint64), int(_RANDOM.integers(1, 1 << 62)) * 2 + 1
_PLACES = _RANDOM.integers(1, 1 << 63, 64).astype(np.uint64) | np.uint64(1)
_SPACE = np.isin(np.arange(256), list(b" \t\n\r\f"))


def _row_marks(data: np.ndarray, at: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(text, mark) of each row of ``n`` words of the texts at data[at[i] : at[i + 1]]; a shorter text is one row.

    Equal rows have equal marks; unequal ones hardly ever do, so who needs certainty compares the rows.
    """
    inside, edge = ~_SPACE[data], np.zeros(len(data) + 1, dtype=bool)
    edge[at] = True
    before, after = np.append(False, inside[:-1]), np.append(inside[1:], False)
    starts, ends = np.flatnonzero(inside & (~before | edge[:-1])), np.flatnonzero(inside & (~after | edge[1:])) + 1
    if not len(starts):
        return starts, starts.astype(np.uint64)
    # a word's bytes are a number to an odd base: a difference of running sums, brought down to the word's start
    powers, back = (np.concatenate([np.ones(1, dtype=np.uint64), np.cumprod(np.full(len(data), b % 2**64, dtype=np.uint64))]) for b in (_BASE, pow(_BASE, -1, 2**64)))
    sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(_BYTES[data] * powers[:-1])])
    word = (sums[ends] - sums[starts]) * back[starts]
    word = (word ^ (word >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    word ^= word >> np.uint64(29)
    text = np.searchsorted(at, starts, side="right") - 1
    first = np.append(True, text[1:] != text[:-1])
    left = np.searchsorted(text, text, side="right") - np.arange(len(text))
    marks = np.zeros(len(word), dtype=np.uint64)
    for k in range(min(n, len(word))):
        marks[: len(word) - k] += np.where(left[: len(word) - k] > k, word[k:], np.uint64(0)) * (_PLACES[k % 64] + np.uint64(2 * (k // 64)))
    whole = (left >= n) | first
    return text[whole], marks[whole]


def _slices(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(a, z, bytes, starts) of the texts in the last column, about SLICE bytes at once."""
    texts = pc.fill_null(batch.column(batch.num_columns - 1), "")
    lengths = np.concatenate([[0], np.cumsum(np.asarray(pc.binary_length(texts)).astype(np.int64))])
    a = 0
    while a < batch.num_rows:
        z = max(a + 1, int(np.searchsorted(lengths, lengths[a] + SLICE, side="right")) - 1)
        yield a, z, np.frombuffer(b"".join(texts.slice(a, z - a).cast(pa.binary()).to_pylist()), dtype=np.uint8), lengths[a : z + 1] - lengths[a]
        a = z


def _meeting(docs: DataFrame, rows: DataFrame, n: int) -> DataFrame:
    """``docs`` (its last column: a text) without the texts that share no row of ``n`` words with the one column of ``rows``.

    Some others may be left; the caller compares what is left.  ``rows`` is a written table.  If it has very many rows of
    words, ``docs`` come back whole.
    """

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, data, at in _slices(batch):
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(_row_marks(data, at, n)[1]).view(np.int64))], names=["mark"])

    marks = rows.mapInArrow(marked, "mark long").distinct().limit(MARKS + 1).toArrow().column(0).to_numpy()
    if len(marks) > MARKS:
        return docs
    shared = docs.sparkSession.sparkContext.broadcast(np.sort(marks.view(np.uint64)))

    def sifted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = shared.value
        for batch in batches:
            for a, z, data, at in _slices(batch):
                text, mark = _row_marks(data, at, n)
                met = np.zeros(z - a, dtype=bool)
                if len(wanted) and len(mark):
                    met[text[wanted[np.minimum(np.searchsorted(wanted, mark), len(wanted) - 1)] == mark]] = True
                if met.any():
                    yield batch.slice(a, z - a).filter(pa.array(met))

    return docs.mapInArrow(sifted, docs.schema)


def overlap(docs: DataFrame, bench: DataFrame, n: int = 8) -> DataFrame:
    """(doc_id, item_id, overlap): share of an item's distinct n-grams that a document has; only pairs that share any.

    Most documents share none and are sifted out by cheap marks of their rows of words; grams are made of the others.
    """
    item = stash(_gram_hashes(bench, "item_id", n), "item-grams")
    sizes = stash(item.groupBy("item_id").agg(F.count(F.lit(1)).alias("size")), "item-sizes")
    lowered = docs.select("doc_id", F.lower("text").alias("text"))
    near = _meeting(lowered, bench.select(F.lower("text").alias("text")), n)
    hits = _gram_hashes(near, "doc_id", n, lowered=True).join(small(item, 40), "g").groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("shared"))
    return hits.join(small(sizes, 40), "item_id").select("doc_id", "item_id", (F.col("shared") / F.col("size")).alias("overlap"))


def contains(docs: DataFrame, bench: DataFrame, anchor: int = 5) -> DataFrame:
    """(doc_id, item_id): documents with an item's text verbatim.

    The words of an item but for its first and last stand as words in every text that contains it: up to ``anchor`` of them,
    in a row, are looked up among the documents' rows of words, and the texts that meet are searched.  Items of fewer than three
    words are searched for in every text; they are broadcast if counted as few.
    """
    inner = words("item")
    items = bench.select("item_id", F.col("text").alias("item")).where(F.col("item").isNotNull()).withColumn("inner", F.slice(inner, 2, F.greatest(F.size(inner) - 2, F.lit(0))))
    items = stash(items.withColumn("g", F.least(F.size("inner"), F.lit(anchor))), "items")
    sizes = sorted(r[0] for r in items.select("g").distinct().collect())  # at most anchor + 1 numbers
    docs = docs.select("doc_id", "text").where(F.col("text").isNotNull())
    out = docs.join(small(items.where("g = 0").select("item_id", "item"), 200), F.col("text").contains(F.col("item"))).select("doc_id", "item_id")
    for n in (n for n in sizes if n):
        keyed = items.where(F.col("g") == n).select("item_id", "item", F.xxhash64(F.slice("inner", 1, n)).alias("mark"))
        keyed = keyed.join(small(stash(keyed.select("mark").distinct(), "marks"), 40), "mark")
        near = _meeting(docs, items.where(F.col("g") == n).select(F.array_join(F.slice("inner", 1, n), " ").alias("text")), n)
        near = near if near is docs else stash(near, "near")
        ws = near.select("doc_id", "text", words("text").alias("w")).where(F.size("w") >= n)
        marks = F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.xxhash64(F.slice("w", i + 1, F.lit(n)))))
        met = ws.select("doc_id", F.explode(marks).alias("mark")).join(small(stash(keyed, "anchors"), 400), "mark").select("doc_id", "item_id", "item")
        out = out.unionAll(met.join(near, "doc_id").where(F.col("text").contains(F.col("item"))).select("doc_id", "item_id"))
    return out


def decontaminate(docs: DataFrame, bench: DataFrame, n: int = 8, threshold: float = 0.5, mode: str = "ngram") -> tuple[DataFrame, DataFrame]:
    """Documents kept, and the audit of those that left.

    mode: 'ngram' (an item's grams by share), 'contains' (verbatim), 'minhash' (a document near to an item as a whole:
    candidates share a band of minima, and the similarity is that of the whole gram sets).
    """
    if mode == "contains":
        audit = contains(docs, bench).withColumn("overlap", F.lit(1.0))
    elif mode == "ngram":
        audit = overlap(docs, bench, n).where(F.col("overlap") >= threshold)
    else:
        hashes, bands = 64, 32  # bands of two: pairs of 0.5 are missed once in ten thousand
        ours, theirs = stash(_gram_sets(docs, "doc_id", 3), "grams"), stash(_gram_sets(bench, "item_id", 3), "item-grams")
        marked = stash(_buckets(_minima(theirs, "item_id", hashes), "item_id", bands), "item-buckets")
        pairs = stash(_buckets(stash(_minima(ours, "doc_id", hashes), "sig"), "doc_id", bands).join(small(marked, 40), "bucket").select("doc_id", "item_id").distinct(), "pairs")
        a, b = ours.withColumnRenamed("grams", "ga"), theirs.withColumnRenamed("grams", "gb")
        both = pairs.join(a, "doc_id").join(b, "item_id").select("doc_id", "item_id", F.size(F.array_intersect("ga", "gb")).alias("both"), (F.size("ga") + F.size("gb")).alias("sum"))
        audit = both.select("doc_id", "item_id", (F.col("both") / (F.col("sum") - F.col("both"))).alias("overlap")).where(F.col("overlap") >= threshold)
    audit = stash(audit, "audit")
    return docs.join(audit.select("doc_id").distinct(), "doc_id", "left_anti"), audit


def dedup_exact(docs: DataFrame) -> DataFrame:
    """The lowest id of each text; the shuffle carries a digest and an id."""
    marked = docs.withColumn("__mark", F.sha2(F.coalesce("text", F.lit("")), 256))
    first = marked.groupBy("__mark").agg(F.min("doc_id").alias("doc_id")).select("doc_id")
    return marked.join(first, "doc_id", "left_semi").drop("__mark")


def _minima(sets: DataFrame, key: str, hashes: int) -> DataFrame:
    """(key, sig): minima of ``hashes`` keyed hashes over the grams of each set."""
    grams = sets.select(key, F.explode("grams").alias("g"))
    return grams.groupBy(key).agg(F.array(*[F.min(F.xxhash64(F.lit(i), "g")) for i in range(hashes)]).alias("sig"))


def minhash(docs: DataFrame, hashes: int = 64, n: int = 5) -> DataFrame:
    """(doc_id, sig): minima of ``hashes`` keyed hashes over the distinct n-word grams, in built-in functions."""
    return _minima(_gram_sets(docs, "doc_id", n), "doc_id", hashes)


def _buckets(sig: DataFrame, key: str, bands: int) -> DataFrame:
    """(key, bucket): a row for each band of minima."""
    rows = F.size("sig") / bands
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.slice("sig", (b * rows + 1).cast("int"), rows.cast("int"))))
    return sig.select(key, F.explode(keys).alias("bucket"))


def near_links(docs: DataFrame, hashes: int = 64, bands: int = 16, threshold: float = 0.8, n: int = 5, rounds: int = 40) -> DataFrame:
    """(key, component) of the documents (unique ids) linked with others: their sets of n-word grams have that similarity.

    Documents of a bucket (equal minima in a band) are candidates.  First all meet the bucket's first; then, while a bucket
    holds several components, documents outside its largest one lead in turn, twice as many each round, until every one
    of them has met the whole bucket.  So all pairs of a bucket that could still join components are judged, on whole sets.
    """
    sets = stash(_gram_sets(docs, "doc_id", n), "grams")
    sig = stash(_minima(sets, "doc_id", hashes), "sig")
    buckets = stash(_buckets(sig, "doc_id", bands), "buckets")
    sizes = stash(buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("lead")).where("n > 1"), "leads")
    shared = stash(spread(buckets, sizes, ["bucket"]).select("bucket", "doc_id", "lead"), "shared")
    x, y = sets.select(F.col("doc_id").alias("a"), F.col("grams").alias("ga")), sets.select(F.col("doc_id").alias("b"), F.col("grams").alias("gb"))

    def judged(pairs: DataFrame) -> DataFrame:
        alike = F.least(F.size("ga"), F.size("gb")) >= F.lit(threshold) * F.greatest(F.size("ga"), F.size("gb"))
        both = pairs.distinct().join(x, "a").join(y, "b").where(alike).select("a", "b", F.size(F.array_intersect("ga", "gb")).alias("both"), (F.size("ga") + F.size("gb")).alias("sum"))
        return both.where(F.col("both") >= F.lit(threshold) * (F.col("sum") - F.col("both"))).select("a", "b")

    links = stash(judged(shared.where("doc_id <> lead").select(F.col("lead").alias("a"), F.col("doc_id").alias("b"))), "near")
    met = stash(shared.select("bucket", F.col("lead").alias("doc_id")).distinct(), "met")
    for turn in range(rounds):
        found = stash(components(links), "found")
        seen = shared.select("bucket", "doc_id").join(found.withColumnRenamed("key", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
        by = seen.groupBy("bucket", "component").agg(F.count(F.lit(1)).alias("c")).groupBy("bucket").agg(F.max(F.struct("c", "component")).alias("main"), F.count(F.lit(1)).alias("kinds"), F.sum("c").alias("n"))
        mixed = stash(by.where("kinds > 1").select("bucket", F.col("main.component").alias("main"), "n"), "mixed")
        rest = stash(spread(seen, mixed, ["bucket"]), "rest")
        order = Window.partitionBy("bucket").orderBy("doc_id")
        leads = rest.where("component <> main").join(met, ["bucket", "doc_id"], "left_anti").withColumn("turn", F.row_number().over(order)).where(F.col("turn") <= 2**turn)
        leads = stash(leads.select("bucket", "doc_id", "component"), "leaders")
        if leads.isEmpty():
            return found
        lead = leads.select("bucket", F.col("doc_id").alias("lead"), F.col("component").alias("own"))
        pairs = rest.join(lead, "bucket").where("component <> own").select(F.least("lead", "doc_id").alias("a"), F.greatest("lead", "doc_id").alias("b"))
        links = stash(links.unionAll(judged(pairs)), "near")
        met = stash(met.unionAll(leads.select("bucket", "doc_id")), "met")
        for used in (mixed, rest):
            release(used)
    raise RuntimeError("near copies did not settle")


def dedup_near(docs: DataFrame, hashes: int = 64, bands: int = 16, threshold: float = 0.8, n: int = 5) -> DataFrame:
    """One survivor (lowest id) per group of near copies; ids are unique, texts without words are kept."""
    found = near_links(docs, hashes, bands, threshold, n)
    return docs.join(found.where("key <> component").select(F.col("key").alias("doc_id")), "doc_id", "left_anti")
