"""Near-duplicate groups by MinHash bands, with odd sketches between the bands and the exact check.

A document is the set of its distinct k-word shingles.  Documents with equal sets form a class.  One pass over
the texts gives each class ``bands * rows`` MinHash samples.  Bands of samples propose pairs; each pair's odd
sketches (parity bitmaps of all samples, so that the XOR's population count tells how many samples differ) drop
those that are far too different; the survivors are confirmed on full shingle sets.

A bucket of n classes proposes n - 1 pairs with its smallest member, never all pairs.  After the first
components, what buckets that still hold several components have outside their largest one is compared with the rest
of the bucket, in blocks: by sketches first, then by an incidence product of the few that are left.  Only joining links
come out, so links that no leader saw are found as well.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.graph import components
from curator.functions.joins import small, spread
from curator.functions.workspace import release, stash
from curator.llm import flat
from curator.llm.rows import keyed, per_row

_U = np.uint64
SHINGLE_WORDS = 5
BANDS, ROWS = 40, 5
#: Bits of a parity bitmap.
SKETCH_BITS = 1024
#: Documents and shingles that a block of a bucket has on average at most.
BLOCK, BLOCK_SHINGLES = 2048, 1 << 20
#: Bytes of two texts' pairs that are judged at once.
PAIR_BYTES = 4 << 20


def shingle_sets(words: flat.Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, text after text, and the bounds (n+1)."""
    n = len(words.first) - 1
    counts = words.counts
    at = flat.gram_starts(words.first, k)
    hashes = flat.grams(words.hashes, k)[at] if len(at) else np.zeros(0, dtype=_U)
    owner = words.owners()[at]
    few = np.flatnonzero((counts > 0) & (counts < k))
    if len(few):
        whole = np.array([flat.grams(words.hashes[words.first[d] : words.first[d + 1]], int(counts[d]))[0] for d in few], dtype=_U)
        hashes, owner = np.concatenate([hashes, whole]), np.concatenate([owner, few])
    order = np.lexsort((hashes, owner))
    hashes, owner = hashes[order], owner[order]
    if len(hashes):
        new = np.ones(len(hashes), dtype=bool)
        new[1:] = (hashes[1:] != hashes[:-1]) | (owner[1:] != owner[:-1])
        hashes, owner = hashes[new], owner[new]
    return hashes, np.searchsorted(owner, np.arange(n + 1))


def _multipliers(n: int) -> np.ndarray:
    return np.random.default_rng(20240607).integers(1, 1 << 63, n, dtype=np.uint64) * _U(2) + _U(1)


def samples(hashes: np.ndarray, bounds: np.ndarray, n: int) -> np.ndarray:
    """n MinHash samples for each non-empty set: (sets, n)."""
    begins = bounds[:-1][np.diff(bounds) > 0]
    out = np.empty((len(begins), n), dtype=_U)
    step = 1 << 15
    groups, i = [], 0
    while i < len(begins):  # runs of sets that stay within the cache
        j = max(i + 1, int(np.searchsorted(begins, begins[i] + step)))
        groups.append((i, j))
        i = j
    factors = _multipliers(n)
    for i, j in groups:
        lo, hi = begins[i], begins[j] if j < len(begins) else len(hashes)
        part, at = hashes[lo:hi], begins[i:j] - lo
        for k in range(n):
            out[i:j, k] = np.minimum.reduceat(part * factors[k], at)
    return out


def odd_sketches(taken: np.ndarray, bits: int = SKETCH_BITS) -> np.ndarray:
    """Parity bitmap of the numbered samples of each set: (sets, bits / 64)."""
    spots = flat.mix(taken ^ _multipliers(taken.shape[1])[None, :], 77) % _U(bits)
    cells = np.zeros((len(taken), bits), dtype=np.uint8)
    np.add.at(cells, (np.arange(len(taken))[:, None], spots.astype(np.int64)), 1)
    return np.packbits(cells & 1, axis=1)


def most_parity(n: int, least: float, bits: int = SKETCH_BITS) -> int:
    """Population count of the XOR that pairs of at least ``least`` similarity stay under (six deviations)."""
    share = max(0.0, least - 6 * np.sqrt(least * (1 - least) / n))
    changed = 2 * n * (1 - share)
    expected = bits / 2 * (1 - (1 - 2 / bits) ** changed)
    return int(expected + 6 * np.sqrt(bits) / 2)


def _signatures(k: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column(0)
            for i, j, words in flat.word_runs(batch.column(1), "space", True):
                hashes, bounds = shingle_sets(words, k)
                sizes = np.diff(bounds)
                full = np.flatnonzero(sizes)
                taken = samples(hashes, bounds, bands * rows)
                # all of a set in two numbers
                sums = [np.add.reduceat(flat.mix(hashes, s), bounds[:-1][full]) if len(full) else np.zeros(0, dtype=_U) for s in (11, 12)]
                ident = np.zeros((j - i, 2), dtype=_U)
                ident[full] = np.stack(sums, axis=1) if len(full) else 0
                band = np.zeros((len(full), bands), dtype=_U)
                for b in range(bands):
                    h = np.full(len(full), b, dtype=_U)
                    for r in range(rows):
                        h = flat.mix(h + taken[:, b * rows + r], b + 1)
                    band[:, b] = h
                size = np.zeros(j - i + 1, dtype=np.int64)
                size[1:][full] = 1
                steps = np.cumsum(size)
                yield pa.RecordBatch.from_arrays(
                    [
                        keys.slice(i, j - i),
                        pa.array(sizes.astype(np.int64)),
                        pa.array(flat.signed(ident[:, 0].copy())),
                        pa.array(flat.signed(ident[:, 1].copy())),
                        flat.pack(odd_sketches(taken), steps * (SKETCH_BITS // 8)),
                        flat.pack(band, steps * bands),
                    ],
                    names=["key", "n_shingles", "set_a", "set_b", "sketch", "bands"],
                )

    return run


def signatures(docs: DataFrame, k: int, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(key, text) -> (key, n_shingles, set_a, set_b, sketch, bands)."""
    return docs.select("key", "text").mapInArrow(_signatures(k, bands, rows), "key long, n_shingles long, set_a long, set_b long, sketch binary, bands binary")


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, at = flat.buffers(batch.column(1))
        values = np.frombuffer(data.tobytes(), dtype=np.int64)
        each = np.diff(at) // 8
        keys = np.repeat(batch.column(0).to_numpy(), each)
        for i in range(0, len(values), 1 << 18):
            yield pa.RecordBatch.from_arrays([pa.array(values[i : i + (1 << 18)]), pa.array(keys[i : i + (1 << 18)])], names=["bucket", "key"])


def _sets(keys: np.ndarray, column: pa.Array, k: int) -> list[np.ndarray]:
    """Shingle sets of a column of texts; a key that comes again is not read again."""
    _, at, which = np.unique(keys, return_index=True, return_inverse=True)
    out: list[np.ndarray] = []
    for _, _, words in flat.word_runs(column.take(pa.array(at)), "space", True):
        hashes, bounds = shingle_sets(words, k)
        out += [hashes[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
    return [out[i] for i in which.tolist()]


def _confirm(k: int, percent: int):
    """Exact check of pairs of texts on their full shingle sets, some bytes of text at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            sizes = np.diff(flat.buffers(whole.column(2))[1]) + np.diff(flat.buffers(whole.column(3))[1])
            for i, j in flat.slices(np.concatenate([[0], np.cumsum(sizes)]), PAIR_BYTES):
                batch = whole.slice(i, j - i)
                ok = []
                for x, y in zip(*(_sets(batch.column(c).to_numpy(), batch.column(c + 2), k) for c in (0, 1)), strict=True):
                    both = len(np.intersect1d(x, y, assume_unique=True))
                    ok.append(100 * both >= percent * (len(x) + len(y) - both))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ok, type=pa.bool_())], names=["a", "b", "linked"])

    return run


def _suspects(percent: int, limit: int):
    """Of two blocks of a bucket, the documents whose sketch and size allow a link to one of the other block in another component."""

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        left = table["left"].to_numpy()
        x, y = np.flatnonzero(left), np.flatnonzero(~left)
        bits = np.frombuffer(flat.buffers(table["sketch"])[0].tobytes(), dtype=_U).reshape(len(left), -1)
        size, comp = table["n_shingles"].to_numpy(), table["component"].to_numpy()
        keep = np.zeros(len(left), dtype=bool)
        for a in range(0, len(x), 32):
            part = x[a : a + 32]
            off = np.bitwise_count(bits[part][:, None, :] ^ bits[y][None, :, :]).sum(axis=2, dtype=np.int32)
            least, most = np.minimum(size[part][:, None], size[y][None, :]), np.maximum(size[part][:, None], size[y][None, :])
            may = (off <= limit) & (100 * least >= percent * most) & (comp[part][:, None] != comp[y][None, :])
            keep[part] |= may.any(axis=1)
            keep[y] |= may.any(axis=0)
        return table.select(["bucket", "i", "j", "left", "key", "component"]).filter(pa.array(keep))

    return run


def _between(k: int, percent: int):
    """Links between two blocks' documents of different components: enough of them to join what belongs together.

    All pairs are judged exactly, by a product of the blocks' incidence matrices, some shingles at a time.
    """

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        keys, comps, left = table["key"].to_numpy(), table["component"].to_numpy(), table["left"].to_numpy()
        parts = []
        for i, _, words in flat.word_runs(table["text"], "space", True):
            hashes, bounds = shingle_sets(words, k)
            parts.append((hashes, np.repeat(np.arange(len(bounds) - 1) + i, np.diff(bounds))))
        hashes, owner = (np.concatenate(x) for x in zip(*parts, strict=True))
        sizes = np.bincount(owner, minlength=len(keys))
        _, column, often = np.unique(hashes, return_inverse=True, return_counts=True)
        held = often[column] > 1
        column, owner = column[held], owner[held]
        order = np.argsort(column, kind="stable")
        column, owner = column[order], owner[order]
        column = np.cumsum(np.concatenate([[0], np.diff(column) != 0])) if len(column) else column
        sides = [np.flatnonzero(left), np.flatnonzero(~left)]
        place = np.empty(len(keys), dtype=np.int64)
        for side in sides:
            place[side] = np.arange(len(side))
        x, y = sides
        both = np.zeros((len(x), len(y)), dtype=np.float32)
        at = 0
        while at < len(column):
            stop = int(np.searchsorted(column, column[at] + 1024))
            grids = []
            for side, mine in zip(sides, (left[owner[at:stop]], ~left[owner[at:stop]]), strict=True):
                grid = np.zeros((len(side), 1024), dtype=np.float32)
                grid[place[owner[at:stop][mine]], column[at:stop][mine] - column[at]] = 1
                grids.append(grid)
            both += grids[0] @ grids[1].T
            at = stop
        linked = (100 * both >= percent * (sizes[x][:, None] + sizes[y][None, :] - both)) & (comps[x][:, None] != comps[y][None, :])
        head = {c: c for c in comps.tolist()}

        def top(c: int) -> int:
            while head[c] != c:
                head[c] = c = head[head[c]]
            return c

        out = []
        for i, j in zip(*(side.tolist() for side in np.nonzero(linked)), strict=True):
            p, q = top(int(comps[x[i]])), top(int(comps[y[j]]))
            if p != q:
                head[max(p, q)] = min(p, q)
                out.append((int(keys[x[i]]), int(keys[y[j]])))
        return pa.table({"a": pa.array([o[0] for o in out], pa.int64()), "b": pa.array([o[1] for o in out], pa.int64())})

    return run


def _across(shared: DataFrame, heads: DataFrame, found: DataFrame, docs: DataFrame, k: int, percent: int, limit: int) -> DataFrame:
    """(a, b): the links within buckets that no leader saw.

    Only buckets that still hold several components are looked at, and of those with the same members one.  A link that
    is left has an end outside the bucket's largest component, so the documents out there, in blocks, meet all of the
    bucket's, in blocks.  Sketches and sizes drop nearly all of them before a text is read.
    """
    seen = shared.join(found, "key", "left").select("bucket", "key", F.coalesce("component", "key").alias("component"))
    seen = stash(seen.join(heads.select("key", "n_shingles"), "key"), "seen")
    mark = [F.bit_xor(F.xxhash64(F.lit(salt), "key")).alias(f"m{salt}") for salt in (1, 2)]
    by = seen.groupBy("bucket", "component").agg(F.count(F.lit(1)).alias("c"), F.sum("n_shingles").alias("s"), *mark)
    by = by.groupBy("bucket").agg(
        F.count(F.lit(1)).alias("kinds"), F.sum("c").alias("n"), F.sum("s").alias("s"), F.bit_xor("m1").alias("m1"), F.bit_xor("m2").alias("m2"), F.max(F.struct("c", "component", "s")).alias("main")
    )
    mixed = by.where("kinds > 1 and n > 2").dropDuplicates(["n", "m1", "m2"])
    blocks = lambda count, shingles: F.ceil(F.greatest(count / F.lit(BLOCK), shingles / F.lit(BLOCK_SHINGLES))).cast("int")
    mixed = mixed.select("bucket", "n", F.col("main.component").alias("main"), blocks(F.col("n"), F.col("s")).alias("all_blocks"), blocks(F.col("n") - F.col("main.c"), F.col("s") - F.col("main.s")).alias("few_blocks"))
    mixed = stash(mixed, "mixed")
    rows = spread(seen.select("bucket", "key", "component", "n_shingles"), mixed, ["bucket"])
    at = lambda salt, n: F.pmod(F.xxhash64(F.lit(salt), "key"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    few = rows.where("component <> main").withColumn("i", at(3, "few_blocks")).withColumn("j", every("all_blocks")).withColumn("left", F.lit(True))
    whole = rows.withColumn("j", at(4, "all_blocks")).withColumn("i", every("few_blocks")).withColumn("left", F.lit(False))
    names = ["bucket", "i", "j", "left", "key", "component", "n_shingles"]
    meet = few.select(names).unionAll(whole.select(names)).join(heads.select("key", "sketch"), "key").select(*names, "sketch")
    kinds = "bucket long, i int, j int, left boolean, key long, component long"
    close = stash(meet.groupBy("bucket", "i", "j").applyInArrow(_suspects(percent, limit), kinds), "suspects")
    ids = stash(close.select("key").distinct(), "ids")
    texts = docs.join(small(ids, 40), "key", "left_semi")
    meet = close.join(texts, "key").select("bucket", "i", "j", "left", "key", "component", "text")
    out = stash(meet.groupBy("bucket", "i", "j").applyInArrow(_between(k, percent), "a long, b long"), "more")
    for used in (seen, mixed, close, ids):
        release(used)
    return out


def near_groups(docs: DataFrame, k: int = SHINGLE_WORDS, percent: int = 80, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(key, text) with unique keys -> (key, n_shingles, component, kept).

    Lower-cases A-Z; words are runs of non-blank bytes.  A text of fewer than k words is one shingle; null or
    blank texts have an empty set, size 0, and are linked with nothing.  Two documents are linked if
    100 * |intersection| >= percent * |union|; ``component`` is the smallest key reachable.
    """
    sigs = stash(signatures(docs, k, bands, rows), "sigs")
    identity = ["n_shingles", "set_a", "set_b"]
    full = sigs.where("n_shingles > 0")
    classes = stash(full.groupBy(*identity).agg(F.min("key").alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1"), "classes")
    member = spread(full.select("key", *identity), classes, identity, "left").select("key", F.coalesce("head", "key").alias("head"))
    member = stash(member, "heads")
    heads = full.join(member.where("key = head").select("key"), "key", "left_semi")
    heads = stash(heads.select("key", "n_shingles", "sketch", "bands"), "reps")
    loose = heads.select("key", "bands").mapInArrow(_unpack, "bucket long, key long")
    lead = stash(loose.groupBy("bucket").agg(F.min("key").alias("lead"), F.count(F.lit(1)).alias("n")).where("n > 1"), "leads")
    shared = stash(spread(loose, lead, ["bucket"]).select("bucket", "key", "lead"), "buckets")
    for used in (classes, lead):
        release(used)

    limit = most_parity(bands * rows, percent / 100)
    x, y = (heads.select("key", "n_shingles", "sketch").toDF(side, f"n{side}", f"s{side}") for side in "ab")
    first = shared.where("key <> lead").select(F.col("lead").alias("a"), F.col("key").alias("b")).distinct()
    near = first.join(x, "a").join(y, "b").where(100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    # pairs whose sketches differ too much are told apart without their texts
    near = stash(near.select("a", "b", _parity("sa", "sb").alias("off")).where(F.col("off") <= limit).select("a", "b"), "near")
    ids = stash(near.select(F.col("a").alias("key")).unionAll(near.select(F.col("b").alias("key"))).distinct(), "ids")
    texts = stash(docs.join(small(ids, 40), "key", "left_semi"), "texts")
    pairs = near.join(texts.toDF("a", "ta"), "a").join(texts.toDF("b", "tb"), "b").select("a", "b", "ta", "tb")
    checked = stash(pairs.mapInArrow(_confirm(k, percent), "a long, b long, linked boolean").where("linked").select("a", "b"), "checked")
    for used in (near, ids, texts):
        release(used)
    found = stash(components(checked), "found")
    more = _across(shared, heads, found, docs, k, percent, limit)
    # on from the components found so far, which are stars
    final = found if more.isEmpty() else stash(components(found.toDF("a", "b").unionAll(more)), "found")
    for used in (shared, heads, checked, more):
        release(used)

    out = sigs.select("key", "n_shingles").join(member, "key", "left").join(final.withColumnRenamed("key", "head"), "head", "left")
    out = out.select("key", "n_shingles", F.coalesce("component", "head", "key").alias("component"))
    # a class is known by its smallest key, so the smallest key of a component is that of a class in it
    return out.withColumn("kept", F.col("key") == F.col("component"))


def _parity(a: str, b: str):
    """Bits that differ between two equally long binary columns."""
    from pyspark.sql.pandas.functions import pandas_udf

    @pandas_udf("int")
    def off(x, y):
        import pandas as pd

        if not len(x):
            return pd.Series([], dtype="int32")
        p = np.frombuffer(b"".join(x), dtype=np.uint8) ^ np.frombuffer(b"".join(y), dtype=np.uint8)
        return pd.Series(np.bitwise_count(p).reshape(len(x), -1).sum(axis=1, dtype=np.int32))

    return off(a, b)


def near_duplicates(docs: DataFrame, k: int = SHINGLE_WORDS, percent: int = 80) -> DataFrame:
    """documents -> (doc_id, n_shingles, component_id, kept), one row per input row.

    Rows that repeat a document's id and text share its result.  Other columns are ignored.
    """
    base, rows = keyed(docs)
    out = near_groups(base, k, percent)
    if rows is None:
        return out.select(F.col("key").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"), "kept")
    ids = rows.groupBy("key").agg(F.first("doc_id").alias("component_id"))
    out = out.join(ids.withColumnRenamed("key", "component"), "component").select("key", "n_shingles", "component_id", "kept")
    return per_row(out, rows)
