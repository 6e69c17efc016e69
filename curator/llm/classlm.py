"""Class-based n-gram scores of texts (Brown classes by exchange clustering).

Counting passes run over all training documents.  The ``HEAD`` most frequent words get ``CLASSES`` classes by the
exchange algorithm.  One exchange step then moves every other word of at least ``LEAST`` occurrences into the class that
its neighbours' classes, counted over the whole corpus, speak for most; all words take that step side by side, against
the head's table.  Rarer words, and those never seen, are classed by their last two bytes into ``SHAPES`` classes, whose
emission is the absolutely discounted word frequency; what the discount frees is the probability of an unseen word,
which counts as one more type, as in the base score.  A text's score is the sum over its tokens of
log10 P(class | class before) and log10 P(word | class); the end of a text is a class of its own, and the context that a
text begins with.

The words that have exchanged classes travel to all tasks, at most ``FREQUENT`` of them (beyond, the least frequent count
as rare); every other word's count is found by a join on its hash, so the table of counts may be of any size.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from curator.functions.workspace import stash
from curator.llm import flat
from curator.llm.rows import keyed, per_row

_U = np.uint64
HEAD, CLASSES, SHAPES = 1500, 64, 32
#: Occurrences of a word that is classed by its neighbours, and the bound on such words (18 bytes each in every task).
LEAST, FREQUENT = 3, 1 << 19
SWEEPS = 6
#: Weight of a class's overall frequency in a row of transitions.
PRIOR = 5.0
#: Hash of the end token; no word hash is compared with it but by equality of 64 bits.
END = np.int64(-6148914691236517206)


def shapes(words: flat.Words) -> np.ndarray:
    """Class of each word by its last two bytes, A-Z lowered."""
    low = flat._ascii_lower
    last = low[words.data[words.ends - 1]].astype(_U)
    before = np.where(words.ends - words.starts > 1, low[words.data[np.maximum(words.ends - 2, 0)]], 0).astype(_U)
    return (flat.mix(last * _U(256) + before, 41) % _U(SHAPES)).astype(np.int64)


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, words in flat.word_runs(batch.column(0), "space", True):
            h, at, n = np.unique(flat.signed(words.hashes), return_index=True, return_counts=True)
            s = shapes(words)[at]
            yield pa.RecordBatch.from_arrays([pa.array(np.append(h, END)), pa.array(np.append(s, -1).astype(np.int8)), pa.array(np.append(n, j - i))], names=["h", "s", "n"])


def word_counts(train: DataFrame) -> DataFrame:
    """(text) of training documents -> (h, s, c): words by hash with their shape and count, the end token among them."""
    return train.select("text").mapInArrow(_count_words, "h long, s byte, n long").groupBy("h", "s").agg(F.sum("n").alias("c"))


def _find(table: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Place of each hash in a sorted table, or -1."""
    if not len(table):
        return np.full(len(h), -1)
    at = np.searchsorted(table, h)
    at[at == len(table)] = 0
    return np.where(table[at] == h, at, -1)


def _line_up(words: flat.Words, ids: np.ndarray, rows: int, end: int) -> tuple[np.ndarray, np.ndarray]:
    """All tokens of some texts in a row, an end before the first text and after each; and the places of the words."""
    seq = np.full(len(ids) + rows + 1, end, dtype=np.int64)
    place = np.arange(len(ids)) + words.owners() + 1
    seq[place] = ids
    return seq, place


def _count_pairs(shared):
    """Pairs of neighbouring tokens by number: a known word's, its shape's (after the words' numbers), or the end's (the last)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, number, known = shared.value
        m = known + SHAPES + 1
        pairs = np.zeros(m * m, dtype=np.int64)
        for batch in batches:
            for i, j, words in flat.word_runs(batch.column(0), "space", True):
                at = _find(table, flat.signed(words.hashes))
                ids = np.where(at >= 0, number[at], known + shapes(words))
                seq, _ = _line_up(words, ids, j - i, m - 1)
                pairs += np.bincount(seq[:-1] * m + seq[1:], minlength=m * m)
        at = np.flatnonzero(pairs)
        for a in range(0, len(at), 1 << 18):
            part = at[a : a + (1 << 18)]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(pairs[part])], names=["code", "n"])

    return run


def pair_counts(learn: DataFrame, table: np.ndarray, number: np.ndarray, known: int) -> np.ndarray:
    """Square matrix of neighbouring tokens' counts; ``table`` is sorted, and ``known`` bounds what reaches the driver."""
    shared = learn.sparkSession.sparkContext.broadcast((table, np.append(number, 0), known))
    got = learn.mapInArrow(_count_pairs(shared), "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).toArrow()
    m = known + SHAPES + 1
    pairs = np.zeros(m * m)
    pairs[got["code"].to_numpy()] = got["n"].to_numpy()
    return pairs.reshape(m, m)


def _xlogx(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log(np.maximum(x, 1e-300)), 0.0)


def exchange(pairs: np.ndarray, classes: int = CLASSES, sweeps: int = SWEEPS, fixed: int = 2) -> np.ndarray:
    """Classes of the head words (all but the last ``fixed`` of a square count matrix) that keep most mutual information.

    The last ones stay in classes of their own.  Words go in order; each moves to the class that gains most.
    """
    m = len(pairs)
    words = m - fixed
    k = min(classes, max(1, words))
    of = np.append(np.arange(words) % k, k + np.arange(fixed))
    g = k + fixed
    one = np.eye(g)[of]
    table = one.T @ pairs @ one
    right, left = pairs @ one, pairs.T @ one  # to classes after, from classes before
    f = _xlogx

    live = [w for w in range(words) if pairs[w].any() or pairs[:, w].any()]
    for _ in range(sweeps):
        moved = 0
        for w in live:
            c, own = of[w], pairs[w, w]
            r, l_ = right[w], left[w]
            table[c, :] -= r
            table[:, c] -= l_
            table[c, c] += own
            r2, l2 = r.copy(), l_.copy()
            r2[c] -= own
            l2[c] -= own
            rows, cols = table.sum(1), table.sum(0)
            a = table[:k]
            gain = (f(a + r2) - f(a)).sum(1) + (f(table[:, :k].T + l2) - f(table[:, :k].T)).sum(1)
            d = np.arange(k)
            t = table[d, d]
            gain += f(t + r2[d] + l2[d] + own) - f(t + r2[d]) - f(t + l2[d]) + f(t)
            gain -= f(rows[:k] + r2.sum() + own) - f(rows[:k]) + f(cols[:k] + l2.sum() + own) - f(cols[:k])
            best = int(np.argmax(gain))
            if gain[best] <= gain[c] + 1e-9:
                best = c
            table[best, :] += r2
            table[:, best] += l2
            table[best, best] += own
            if best != c:
                moved += 1
                of[w] = best
                right[:, c] -= pairs[:, w]
                right[:, best] += pairs[:, w]
                left[:, c] -= pairs[w]
                left[:, best] += pairs[w]
        if not moved:
            break
    return of


def _contexts(shared):
    """Classes beside the words outside the head: word * 2G + class before, or + G + class after."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, class_of, moves, classes = shared.value
        g = classes + SHAPES + 1
        for batch in batches:
            for i, j, words in flat.word_runs(batch.column(0), "space", True):
                at = _find(table, flat.signed(words.hashes))
                ids = np.where(at >= 0, class_of[at], classes + shapes(words))
                seq, place = _line_up(words, ids, j - i, g - 1)
                mine = np.flatnonzero((at >= 0) & moves[at])
                base, spot = at[mine] * (2 * g), place[mine]
                code, n = np.unique(np.concatenate([base + seq[spot - 1], base + g + seq[spot + 1]]), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(n)], names=["code", "n"])

    return run


def best_classes(bounds: np.ndarray, beside: np.ndarray, n: np.ndarray, pairs: np.ndarray, classes: int) -> np.ndarray:
    """For each word (entries bounds[i]..bounds[i+1]: neighbour class before, or G + class after, and count) the class
    that gains most mutual information by taking it in."""
    g = len(pairs)
    after, n = beside >= g, n.astype(float)
    there = np.where(after[:, None], pairs[:classes, beside % g].T, pairs[beside % g, :classes])
    gain = np.add.reduceat(_xlogx(there + n[:, None]) - _xlogx(there), bounds[:-1], axis=0)
    for side, total in ((after, pairs[:classes].sum(1)), (~after, pairs[:, :classes].sum(0))):
        own = np.add.reduceat(np.where(side, n, 0.0), bounds[:-1])
        gain -= _xlogx(total[None, :] + own[:, None]) - _xlogx(total)[None, :]
    return np.argmax(gain, axis=1)


def _move(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs, classes = shared.value
        for batch in batches:
            lists = batch.column(1)
            entries = lists.flatten()
            beside = entries.field("d").to_numpy(zero_copy_only=False).astype(np.int64)
            n = entries.field("n").to_numpy(zero_copy_only=False)
            bounds = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths()).astype(np.int64))])
            best = np.empty(batch.num_rows, dtype=np.int16)
            for i, j in flat.slices(bounds, 1 << 14):
                lo, hi = bounds[i], bounds[j]
                best[i:j] = best_classes(bounds[i : j + 1] - lo, beside[lo:hi], n[lo:hi], pairs, classes)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(best)], names=["word", "class"])

    return run


def _score_task(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = shared.value
        table, counts, class_of, steps = p["table"], p["counts"], p["class_of"], p["steps"]
        for batch in batches:
            keys = batch.column(0).to_numpy()
            for i, j, words in flat.word_runs(batch.column(1), "space", True):
                rows = j - i
                owner = words.owners()
                h, s = flat.signed(words.hashes), shapes(words)
                at = _find(table, h)
                known = np.flatnonzero(at >= 0)
                cls = p["classes"] + s
                cls[known] = class_of[at[known]]
                c = counts[at[known]]
                seq, _ = _line_up(words, cls, rows, len(steps) - 1)
                text = np.repeat(np.arange(rows), words.counts + 1)
                score = np.bincount(text, weights=steps[seq[:-1], seq[1:]], minlength=rows)
                score += np.bincount(owner[known], weights=np.log10(c / p["class_total"][cls[known]]), minlength=rows)
                base = np.bincount(owner[known], weights=np.log10((c + 0.1) / p["base"]), minlength=rows)
                base += np.log10((p["end_count"] + 0.1) / p["base"])
                n_known = np.bincount(owner[known], minlength=rows) + (p["end_count"] > 0)
                # the others: one row for each text and word, to meet the table of counts
                rare = np.flatnonzero(at < 0)
                tag = flat.mix(words.hashes[rare] ^ flat.mix(owner[rare].astype(_U), 21))
                _, one, n = np.unique(tag, return_index=True, return_counts=True)
                out_key = np.concatenate([keys[i:j], keys[i + owner[rare[one]]]])
                out_h = np.concatenate([flat.signed(flat.mix(np.arange(i, j).astype(_U), 31)), h[rare[one]]])
                out_s = np.concatenate([np.zeros(rows, dtype=np.int64), s[rare[one]]]).astype(np.int32)
                zero = np.zeros(len(one))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(out_key), pa.array(out_h), pa.array(out_s),
                        pa.array(np.concatenate([np.zeros(rows, dtype=np.int64), n])),
                        pa.array(np.concatenate([words.counts + 1, zero.astype(np.int64)])),
                        pa.array(np.concatenate([n_known, zero.astype(np.int64)])),
                        pa.array(np.concatenate([base, zero])), pa.array(np.concatenate([score, zero])),
                    ],
                    names=["key", "h", "s", "times", "n_tokens", "n_known", "base", "score"],
                )

    return run


def language_scores(docs: DataFrame, held: Column | None = None) -> DataFrame:
    """documents -> (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, perplexity) for every row.

    Documents for which ``held`` (on doc_id) holds are not learned from; unless given, those whose crc32(doc_id) mod 10
    is 0.  A null doc_id is learned from.  Null and empty texts have the end token only.  Without training documents
    every word is the unseen one.  Rows that repeat an id and its text are one document, learned from once.
    """
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 10 == 0 if held is None else held
    held = F.coalesce(held, F.lit(False))
    base, rows = keyed(docs)
    source = base.withColumnRenamed("key", "doc_id") if rows is None else rows.dropDuplicates(["key"])
    learn = source.where(~held).select("text")
    counts = stash(word_counts(learn), "counts")
    model = _fit(learn, counts)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kinds = "key long, h long, s int, times long, n_tokens long, n_known long, base double, score double"
    parts = base.select("key", "text").mapInArrow(_score_task(shared), kinds).join(counts.select("h", "c"), "h", "left")
    c = F.coalesce(F.col("c"), F.lit(0)).cast("double")
    times = F.col("times")
    by_shape = lambda values: F.get(F.array(*[F.lit(float(v)) for v in values]), F.col("s"))
    emitted = F.when(c > 0, F.log10(c - F.lit(float(model["discount"]))) - by_shape(model["rare_total"])).otherwise(by_shape(model["unseen"]))
    out = parts.groupBy("key").agg(
        F.sum("n_tokens").alias("n_tokens"),
        F.sum(F.col("n_known") + F.when(c > 0, times).otherwise(0)).alias("n_known"),
        F.sum(F.col("base") + times * F.log10((c + 0.1) / F.lit(float(model["base"])))).alias("base_score"),
        F.sum(F.col("score") + F.when(times > 0, times * emitted).otherwise(0.0)).alias("score"),
    )
    out = per_row(out, rows)
    perplexity = F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens"))
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(model["total"]).cast("long").alias("train_tokens"), "base_score", "score", perplexity.alias("perplexity"))


def _fit(learn: DataFrame, counts: DataFrame) -> dict:
    """The model's arrays; what comes to the driver is bounded by FREQUENT and (HEAD + SHAPES + 1)^2."""
    word = counts.where(F.col("h") != int(END))
    total, distinct, once, twice, end_count = (
        int(x) for x in counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1)), F.count(F.when(F.col("c") == 1, 1)), F.count(F.when(F.col("c") == 2, 1)), F.coalesce(F.sum(F.when(F.col("h") == int(END), F.col("c"))), F.lit(0))).first()
    )
    # the least step of counts whose words, with all more frequent ones, keep within FREQUENT
    step = F.floor(F.log2("c") * 16).cast("int")
    steps = sorted(((r[0], r[1]) for r in word.where(F.col("c") >= LEAST).groupBy(step).agg(F.count(F.lit(1))).collect()), reverse=True)
    least, held = 1 << 30, 0
    for at, n in steps:
        if held + n > FREQUENT:
            break
        held, least = held + n, at
    frequent = (F.col("c") >= LEAST) & (step >= least)
    rows = word.where(frequent).select("h", "c", "s").toArrow()
    h, c, s = (rows[name].to_numpy().astype(np.int64) for name in ("h", "c", "s"))
    order = np.argsort(h)
    h, c, s = h[order], c[order], s[order]
    head = np.lexsort((h, -c))[:HEAD]

    # classes of the head; all other words stand for their shapes
    moves = np.ones(len(h), dtype=bool)
    moves[head] = False
    rank = np.empty(len(h), dtype=np.int64)
    rank[head] = np.arange(len(head))
    pairs = pair_counts(learn, h[~moves], rank[~moves], len(head))
    of = exchange(pairs, fixed=SHAPES + 1)
    classes = int(of[-1]) - SHAPES
    class_of = classes + s
    class_of[head] = of[: len(head)]

    # classes of the other words
    if moves.any():
        context = learn.sparkSession.sparkContext
        one = np.eye(classes + SHAPES + 1)[of]
        provisional, width = one.T @ pairs @ one, 2 * one.shape[1]
        beside = learn.mapInArrow(_contexts(context.broadcast((h, class_of, moves, classes))), "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))
        beside = beside.groupBy(F.expr(f"code div {width}").alias("word")).agg(F.collect_list(F.struct(F.expr(f"cast(code % {width} as int)").alias("d"), "n")).alias("beside"))
        moved = beside.mapInArrow(_move(context.broadcast((provisional, classes))), "word long, class short").toArrow()
        class_of[moved["word"].to_numpy()] = moved["class"].to_numpy()

    pairs = pair_counts(learn, h, class_of, classes)
    # transitions: discounted, the rest by how often each class comes at all
    prior = (pairs.sum(0) + 0.5) / (pairs.sum() + 0.5 * len(pairs))
    flow = (pairs + PRIOR * prior[None, :]) / (pairs.sum(1, keepdims=True) + PRIOR)
    rare_total, rare_kinds = np.zeros(SHAPES), np.zeros(SHAPES)
    for row in word.where(~frequent).groupBy("s").agg(F.sum("c").alias("c"), F.count(F.lit(1)).alias("kinds")).collect():
        rare_total[row["s"]], rare_kinds[row["s"]] = row["c"], row["kinds"]
    discount = (once + 1) / (once + 2 * twice + 2)
    unseen = np.where(rare_kinds > 0, discount * rare_kinds / np.maximum(rare_total, 1), 1.0)
    return {
        "table": h, "counts": c.astype(float), "class_of": class_of.astype(np.int16), "classes": classes, "class_total": np.bincount(class_of, weights=c, minlength=len(pairs)), "steps": np.log10(flow),
        "end_count": end_count, "base": total + 0.1 * (distinct + 1), "total": total, "discount": discount, "rare_total": np.log10(np.maximum(rare_total, 1)), "unseen": np.log10(unseen),
    }
