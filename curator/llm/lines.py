"""Line dedup by pairwise alignment of documents that share runs of lines.

Lines are known by hashes of 64 bits, which are compared within a pair of documents only; runs, which are looked up in
the whole corpus, have 128.  A run is the shortest row of consecutive lines, from a line on or up to a line, that has
at least ``MIN_WORDS`` words; runs of one document may overlap.  Every run that several documents have, however many,
pairs each of its documents with the first one that has it: as many pairs as places, never all pairs of a group.
Each pair is aligned with patience diff on its line hashes alone: equal lines at both ends are matched, then lines that
stand once in both in their longest common order, and so on inside each gap.  Where no line is left that stands once,
and for blocks that were moved or that the later document has again, which no alignment in order reaches, the runs
that proposed the pair are matched one by one.  Blocks of at least ``MIN_WORDS`` words are deleted from the later
document; every line of a block that any earlier document has goes.  The first document that has a run never loses it,
so nothing disappears from the corpus.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.functions.joins import BROADCAST_BYTES, spread
from curator.functions.workspace import release, stash
from curator.llm import flat
from curator.llm.rows import attached, keyed, per_row

MIN_WORDS = 8


def _lines(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin and stop byte of each line and the first line of each text (n+1)."""
    data, offsets = data[int(offsets[0]) : int(offsets[-1])], offsets - offsets[0]
    rows = len(offsets) - 1
    brk = np.flatnonzero(data == 0x0A)
    begins = np.concatenate([offsets[:-1], brk + 1])
    stops = np.concatenate([offsets[1:], brk])
    # stop of each line: the next break or the text's end
    begins = np.sort(begins, kind="stable")
    stops = np.sort(stops, kind="stable")
    owner = np.concatenate([np.arange(rows), np.searchsorted(offsets, brk, side="right") - 1])
    first = np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=rows))])
    return begins, stops, first


def line_arrays(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """i, j, begins, stops, first, hashes and words of each line; white space around words doesn't count."""
    data, offsets = flat.buffers(column)
    for i, j in flat.slices(offsets):
        part = offsets[i : j + 1]
        begins, stops, first = _lines(data, part)
        words = flat.Words(data, part, "space", False)
        w0, w1 = np.searchsorted(words.starts, begins), np.searchsorted(words.starts, stops)
        n = w1 - w0
        h = np.zeros(len(begins), dtype=np.uint64)
        place = np.arange(len(words.hashes)) - np.repeat(w0, n)
        mixed = flat.mix(words.hashes + flat.mix(place.astype(np.uint64), 3), 4)
        sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(mixed)])
        h = flat.mix(sums[w1] - sums[w0] + n.astype(np.uint64), 6)
        yield i, j, begins, stops, first, h, n


def _line_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, _, _, first, h, n in line_arrays(batch.column(1)):
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), flat.pack(h, first), flat.pack(n.astype(np.int32), first)], names=["key", "hashes", "sizes"])


def runs(h: np.ndarray, n: np.ndarray, first: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """First line, last line and both hashes of each run of texts with the line hashes h, words n and bounds first (n+1).

    Runs begin and end at lines with words.  Those from each line on and those up to each line cover every block of
    ``least`` words or more without leaving it.
    """
    m = len(h)
    total = np.concatenate([[0], np.cumsum(n, dtype=np.int64)])
    owner = np.repeat(np.arange(len(first) - 1), np.diff(first))
    line = np.flatnonzero(n > 0)
    to = np.searchsorted(total, total[line] + least, side="left") - 1
    since = np.searchsorted(total, total[line + 1] - least, side="right") - 1
    down, up = to < first[owner[line] + 1], since >= first[owner[line]]
    both = np.unique(np.concatenate([line[down] * m + to[down], since[up] * m + line[up]]))
    begin, last = both // max(1, m), both % max(1, m)
    power, inverse = flat._power_tables(m + 1)
    both_hashes = []
    for salt in (8, 9):
        sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(flat.mix(h, salt) * power[:m])])
        both_hashes.append(flat.mix((sums[last + 1] - sums[begin]) * inverse[begin], salt))
    return begin, last, *both_hashes


def _run_places(least: int):
    """(run, check, key, begin, last): runs of each document by two hashes and the numbers of their lines."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = flat.buffers(batch.column(1))
            sizes, _ = flat.buffers(batch.column(2))
            first = at // 8
            begin, last, h, check = runs(np.frombuffer(data.tobytes(), dtype=np.uint64), np.frombuffer(sizes.tobytes(), dtype=np.int32), first, least)
            owner = np.searchsorted(first, begin, side="right") - 1
            begin, last = (begin - first[owner]).astype(np.int32), (last - first[owner]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(flat.signed(h)), pa.array(flat.signed(check)), pa.array(batch.column(0).to_numpy()[owner]), pa.array(begin), pa.array(last)], names=["run", "check", "key", "begin", "last"])

    return run


def _anchors(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Places of the elements that stand once in both sequences, in their longest common order."""
    once_a: dict[int, int] = {}
    for i, x in enumerate(a):
        once_a[x] = -1 if x in once_a else i
    once_b: dict[int, int] = {}
    for j, x in enumerate(b):
        once_b[x] = -1 if x in once_b else j
    common = sorted((once_a[x], j) for x, j in once_b.items() if j >= 0 and once_a.get(x, -1) >= 0)
    tails: list[int] = []
    picks: list[int] = []
    back = [-1] * len(common)
    for k, (_, j) in enumerate(common):
        at = bisect_left(tails, j)
        back[k] = picks[at - 1] if at else -1
        if at == len(tails):
            tails.append(j)
            picks.append(k)
        else:
            tails[at], picks[at] = j, k
    chain: list[tuple[int, int]] = []
    k = picks[-1] if picks else -1
    while k >= 0:
        chain.append(common[k])
        k = back[k]
    chain.reverse()
    return chain


def patience(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Matched places of two sequences: equal ends, then anchors, then the same inside each gap between them."""
    out: list[tuple[int, int]] = []
    gaps = [(0, len(a), 0, len(b))]
    while gaps:
        i, p, j, q = gaps.pop()
        while i < p and j < q and a[i] == b[j]:
            out.append((i, j))
            i, j = i + 1, j + 1
        while i < p and j < q and a[p - 1] == b[q - 1]:
            p, q = p - 1, q - 1
            out.append((p, q))
        chain = [(i + x, j + y) for x, y in _anchors(a[i:p], b[j:q])] if i < p and j < q else []
        if chain:
            out += chain
            edges = [(i - 1, j - 1), *chain, (p, q)]
            gaps += [(x[0] + 1, y[0], x[1] + 1, y[1]) for x, y in zip(edges, edges[1:])]
    return sorted(out)


def aligned_blocks(a: list[int], b: list[int], sizes: list[int], least: int) -> list[int]:
    """Places of b in aligned blocks of at least ``least`` words (blank lines belong to the block around them)."""
    found, block = [], []
    last = None
    for i, j in [*patience(a, b), (-9, -9)]:
        if last is not None and (i, j) != (last[0] + 1, last[1] + 1):
            if sum(sizes[k] for k in block) >= least:
                found += block
            block = []
        block.append(j)
        last = (i, j)
    return found


def _align(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, gone = [], []
            for key, mine, sizes, other, spans in zip(*(batch.column(c) for c in range(5)), strict=True):
                b = np.frombuffer(mine.as_buffer(), dtype=np.int64).tolist()
                a = np.frombuffer(other.as_buffer(), dtype=np.int64).tolist()
                places = set(aligned_blocks(a, b, np.frombuffer(sizes.as_buffer(), dtype=np.int32).tolist(), least))
                for span in spans.as_py():
                    places.update(range(span >> 32, (span & 0xFFFFFFFF) + 1))
                keys.append(key.as_py())
                gone.append(sorted(places))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(gone, pa.list_(pa.int32()))], names=["key", "gone"])

    return run


def repeated_lines(docs: DataFrame, least: int = MIN_WORDS) -> DataFrame:
    """(key, text) -> (key, gone): numbers of the lines to delete, for documents that lose any."""
    table = stash(docs.select("key", "text").mapInArrow(_line_rows, "key long, hashes binary, sizes binary"), "lines")
    places = stash(table.mapInArrow(_run_places(least), "run long, check long, key long, begin int, last int"), "places")
    run = ["run", "check"]
    firsts = places.groupBy(*run).agg(F.min("key").alias("first"), F.max("key").alias("end"), F.count(F.lit(1)).alias("n")).where("first < end")
    firsts = stash(firsts.select(*run, "first", "n"), "firsts")
    span = F.shiftleft(F.col("begin").cast("long"), 32) + F.col("last")
    met = spread(places, firsts, run).where("key <> first")
    pairs = stash(met.groupBy("key", "first").agg(F.collect_set(span).alias("spans")), "aligned")
    for used in (places, firsts):
        release(used)
    both = pairs.join(table, "key").join(table.select(F.col("key").alias("first"), F.col("hashes").alias("other")), "first").select("key", "hashes", "sizes", "other", "spans")
    found = both.mapInArrow(_align(least), "key long, gone array<int>")
    out = stash(found.groupBy("key").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("gone")))).alias("gone")), "gone")
    for used in (table, pairs):
        release(used)
    return out


def _without(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        gone = batch.column(2)
        for i, j, begins, stops, first, _, _ in line_arrays(batch.column(1)):
            data, offsets = flat.buffers(batch.column(1).slice(i, j - i))
            raw = data.tobytes()
            texts, n_gone, shas = [], [], []
            for d in range(j - i):
                lost = gone[i + d]
                if not lost.is_valid:
                    text = raw[offsets[d] : offsets[d + 1]]
                    n_gone.append(0)
                else:
                    drop = set(lost.as_py())
                    n_gone.append(len(drop))
                    text = b"\n".join(raw[begins[k] : stops[k]] for k in range(int(first[d]), int(first[d + 1])) if k - int(first[d]) not in drop)
                shas.append(hashlib.sha256(text).hexdigest())
                texts.append(text.decode("utf-8", "replace") if batch.column(1)[i + d].is_valid else None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), pa.array(np.diff(first)), pa.array(n_gone, pa.int64()), pa.array(shas, pa.string()), pa.array(texts, pa.string())],
                names=["key", "n_lines", "n_removed", "kept_sha256", "kept_text"],
            )


def line_dedup(docs: DataFrame, least: int = MIN_WORDS) -> DataFrame:
    """documents -> (doc_id, n_lines, n_removed, kept_sha256, kept_text) for every row.

    Lines end at line feeds; white space between and around words doesn't tell lines apart.  A null text stays null
    and has one empty line, as an empty one has.  Rows that repeat an id and its text are one document; "later" is by
    doc_id, then by the text's hash.
    """
    base, rows = keyed(docs)
    gone = repeated_lines(base, least)
    n, width = gone.agg(F.count(F.lit(1)), F.sum(4 * F.size("gone") + 40)).first()
    gone = F.broadcast(gone) if n and width <= BROADCAST_BYTES else gone
    out = base.join(gone, "key", "left").select("key", "text", "gone").mapInArrow(_without, "key long, n_lines long, n_removed long, kept_sha256 string, kept_text string")
    return per_row(out, rows)


def without_repeated_lines(docs: DataFrame, least: int = MIN_WORDS) -> DataFrame:
    """The documents with aligned lines deleted; one of which nothing is left goes, if it had any text.

    Other columns stay, n_chars follows the text.
    """
    rows, base = attached(docs)
    gone = repeated_lines(base, least)
    n, width = gone.agg(F.count(F.lit(1)), F.sum(4 * F.size("gone") + 40)).first()
    gone = F.broadcast(gone) if n and width <= BROADCAST_BYTES else gone
    kept = rows.join(gone.toDF("__key", "__gone"), "__key", "left").drop("__key")
    lines = F.split("text", "\n")
    left = F.array_join(F.filter(F.transform(lines, lambda x, i: F.when(~F.array_contains("__gone", i), x)), lambda x: x.isNotNull()), "\n")
    kept = kept.withColumn("text", F.when(F.col("__gone").isNull(), F.col("text")).otherwise(left))
    kept = kept.where(F.col("__gone").isNull() | F.col("text").rlike(r"[^\x20\x09-\x0D]")).drop("__gone").select(docs.columns)
    return kept.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else kept
