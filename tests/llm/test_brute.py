"""Models, signal features and pipeline stages against plain loops, and all operators on a table of awkward rows."""

from __future__ import annotations

import hashlib
import math
import zlib

import numpy as np
import pyarrow as pa
import pytest
from test_operators import ROWS, alnum, brute_groups, lower, space

from curator.llm import audio, classlm, contamination, flat, licences, lines, near, pieces, spans, toxicity, unigram


def test_ftrl_equals_loops():
    rng = np.random.default_rng(3)
    examples = [np.unique(rng.integers(0, 40, 12)).astype(np.int32) for _ in range(60)]
    labels = (rng.random(60) < 0.4).astype(float)
    alpha, l1 = 0.7, 0.2
    z, n, zb, nb = {}, {}, 0.0, 0.0

    def weight(i):
        zi = z.get(i, 0.0)
        return 0.0 if abs(zi) <= l1 else -(zi - math.copysign(l1, zi)) / ((toxicity.BETA + math.sqrt(n.get(i, 0.0))) / alpha + toxicity.L2)

    for _ in range(3):
        for x, y in zip(examples, labels, strict=True):
            w = {int(i): weight(int(i)) for i in x}
            bias = -zb / ((toxicity.BETA + math.sqrt(nb)) / alpha)
            g = 1 / (1 + math.exp(-(sum(w.values()) + bias))) - y
            for i, wi in w.items():
                sigma = (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / alpha
                z[i], n[i] = z.get(i, 0.0) + g - sigma * wi, n.get(i, 0.0) + g * g
            zb, nb = zb + g - (math.sqrt(nb + g * g) - math.sqrt(nb)) / alpha * bias, nb + g * g
    at, values, bias = toxicity.fit(examples, labels, 3, alpha, l1)
    want = {i: weight(i) for i in z if weight(i)}
    assert dict(zip(at.tolist(), values.tolist(), strict=True)) == pytest.approx(want)
    assert bias == pytest.approx(-zb / ((toxicity.BETA + math.sqrt(nb)) / alpha))


def test_fit_is_bounded_by_features(monkeypatch):
    monkeypatch.setattr(toxicity, "MAX_FEATURES", 100)
    text = " ".join(f"w{i}" for i in range(400))
    batch = pa.RecordBatch.from_arrays([pa.array([text] * 600), pa.array([1.0, 0.0] * 300)], names=["text", "y"])
    seen = []
    monkeypatch.setattr(toxicity, "fit", lambda examples, labels: (seen.append((len(examples), len(labels))), (np.zeros(0, dtype=int), np.zeros(0), 0.0))[1])
    list(toxicity._fit_task(iter([batch, batch])))
    assert seen == [(256, 256)]


def test_class_model_equals_loops(spark, monkeypatch):
    monkeypatch.setattr(classlm, "HEAD", 12)
    monkeypatch.setattr(classlm, "CLASSES", 4)
    rng = np.random.default_rng(1)
    docs = [(i, " ".join(f"W{x}" for x in rng.zipf(1.6, 30) % 60)) for i in range(80)] + [(500, None), (501, "")]
    table = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    learn = table.where("crc32(cast(cast(doc_id as string) as binary)) % 10 <> 0").select("text")
    counts = classlm.word_counts(learn).persist()
    model = classlm._fit(learn, counts)
    count = {r["h"]: r["c"] for r in counts.collect()}
    known, classes = dict(zip(model["table"].tolist(), model["class_of"].tolist(), strict=True)), model["classes"]
    assert len(known) > classlm.HEAD and set(known.values()) <= set(range(classes))
    assert all(count[h] >= classlm.LEAST for h in known)
    # every row of transitions, and every class's emission, is a distribution
    assert np.allclose((10 ** model["steps"]).sum(1), 1)
    for c in set(known.values()):
        assert sum(count[h] for h in known if known[h] == c) == model["class_total"][c]
    shape_of = {}
    for _, t in docs:
        words = flat.Words(*flat.buffers(pa.array([t], pa.string())), "space", True)
        shape_of |= dict(zip(flat.signed(words.hashes).tolist(), classlm.shapes(words).tolist(), strict=True))
    for s in range(classlm.SHAPES):
        rare = [c for h, c in count.items() if h not in known and shape_of.get(h) == s]
        if rare:
            assert sum(c - model["discount"] for c in rare) / 10 ** model["rare_total"][s] + 10 ** model["unseen"][s] == pytest.approx(1)
    for r in classlm.language_scores(table).collect():
        text, want, last = dict(docs)[r["doc_id"]], 0.0, len(model["steps"]) - 1
        for w in space(lower(text)):
            h = int(flat.signed(flat.Words(*flat.buffers(pa.array([w])), "space", True).hashes)[0])
            c = known.get(h, classes + shape_of[h])
            if h in known:
                own = math.log10(count[h] / model["class_total"][c])
            elif h in count:
                own = math.log10(count[h] - model["discount"]) - model["rare_total"][shape_of[h]]
            else:
                own = model["unseen"][shape_of[h]]
            want, last = want + model["steps"][last, c] + own, c
        want += model["steps"][last, len(model["steps"]) - 1]
        assert r["score"] == pytest.approx(want) and r["perplexity"] == pytest.approx(10 ** (-want / r["n_tokens"]))


def test_a_word_moves_where_it_gains_most():
    rng = np.random.default_rng(5)
    pairs, classes = rng.integers(0, 50, (9, 9)).astype(float), 5
    beside, n = np.array([6, 7, 8, 9 + 5, 9 + 7]), np.array([3, 9, 1, 6, 7])
    f = lambda x: sum(v * math.log(v) for v in np.ravel(x) if v > 0)

    def information(c):
        table = pairs.copy()
        for d, m in zip(beside, n, strict=True):
            if d >= 9:
                table[c, d - 9] += m
            else:
                table[d, c] += m
        # the neighbours' own totals don't depend on where the word goes
        return f(table) - f(table.sum(1)[:classes]) - f(table.sum(0)[:classes])

    assert classlm.best_classes(np.array([0, 5]), beside, n, pairs, classes).tolist() == [max(range(classes), key=information)]


def test_resampling_is_a_convolution():
    rng = np.random.default_rng(0)
    for n, up, down in ((1, 3, 4), (50, 3, 4), (200, 1, 2), (90, 5, 3)):
        x = rng.normal(size=n).astype(np.float32)
        taps = audio._phases(up, down)[:, ::-1].T.reshape(-1)
        stuffed = np.zeros(n * up)
        stuffed[::up] = x
        want = np.convolve(stuffed, taps)[: -(-n * up // down) * down : down]
        assert np.allclose(audio.resample(x, up, down), want[: -(-n * up // down)], atol=1e-5)


def test_log_mel_and_segments_equal_loops():
    rng = np.random.default_rng(2)
    x = rng.normal(size=700).astype(np.float32)
    rate = 12000
    got = np.concatenate([m for m, _ in audio.log_mel(x, rate)])
    turn = np.exp(-2j * np.pi * np.outer(np.arange(audio.FRAME // 2 + 1), np.arange(audio.FRAME)) / audio.FRAME)
    mel = lambda f: 2595 * math.log10(1 + f / 700)
    edges = [700 * (10 ** (m / 2595) - 1) for m in np.linspace(mel(20), mel(rate / 2), audio.MELS + 2)]
    for k in range(len(got)):
        frame = np.zeros(audio.FRAME)
        part = x[k * audio.HOP : k * audio.HOP + audio.FRAME]
        frame[: len(part)] = part
        power = np.abs(turn @ (frame * (0.5 - 0.5 * np.cos(2 * np.pi * np.arange(audio.FRAME) / audio.FRAME)))) ** 2
        for b in range(audio.MELS):
            total = 0.0
            for i, p in enumerate(power):
                hz = i * rate / audio.FRAME
                total += p * max(0.0, min((hz - edges[b]) / (edges[b + 1] - edges[b]), (edges[b + 2] - hz) / (edges[b + 2] - edges[b + 1])))
            assert got[k, b] == pytest.approx(math.log(total + 1e-6), abs=2e-3)
    for _ in range(50):
        energy = rng.normal(size=40)
        want, start = [], None
        for i, e in enumerate(energy):
            if start is None and e > 1.0:
                start = i
            elif start is not None and e <= 0.3:
                want.append((start, i))
                start = None
        want += [(start, 40)] if start is not None else []
        assert audio.segments(energy, 0.0, 1.0, 0.3) == want


def test_tensors_come_back(spark):
    docs = spark.createDataFrame([(1, "some text " * 900), (2, None)], "doc_id long, text string")
    for r in audio.audio_features(docs).collect():
        tensors, times = audio.read_tensors(bytes(r["tensors"]))
        seen = audio.Analysis(audio.payload_of((dict([(1, "some text " * 900)]).get(r["doc_id"]) or "").encode()), keep=True)
        assert tensors.shape == (-(-seen.frames // audio.TENSOR_FRAMES), audio.TENSOR_FRAMES, audio.MELS) and len(times) == len(r["spans"])
        assert np.array_equal(tensors.reshape(-1, audio.MELS)[: seen.frames], seen.mels) and times[-1, 1] == r["spans"][-1]["end"]


def test_blocks_find_links_that_no_leader_sees(spark, monkeypatch):
    monkeypatch.setattr(near, "BLOCK", 3)
    words = [f"w{i}" for i in range(60)]
    rows, rng = [], np.random.default_rng(9)
    for _ in range(4):  # chains: neighbours are alike, ends are not
        chain = list(words)
        for _ in range(12):
            rows.append((len(rows), " ".join(chain)))
            for _ in range(2):
                chain[int(rng.integers(0, 60))] = f"e{int(rng.integers(0, 40))}"
    got = near.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 2).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == brute_groups(rows, 2)


def test_all_operators_on_awkward_rows(spark):
    """Nulls, empty and very long texts, repeated rows and clashing columns: a row for each row, equal for equal rows."""
    long = " ".join(f"word{i % 5000} and{i}" for i in range(40_000))
    rows = [*ROWS, (20, long), (21, long + " end"), (20, long)]
    odd = spark.createDataFrame([(i, t, None, "clash", -1) for i, t in rows], "doc_id long, text string, lang string, key string, n_words long").repartition(2)
    labels = spark.createDataFrame([(1, 0), (3, 1), (14, 0), (20, 0)], "doc_id long, toxic int")
    bench = spark.createDataFrame([(1, long[:4000]), (2, None)], "item_id long, text string")
    results = [
        toxicity.toxicity(odd, labels), unigram.token_counts(odd), lines.line_dedup(odd), near.near_duplicates(odd, 2), classlm.language_scores(odd), pieces.encode_decode(odd),
        contamination.contamination(odd, bench), spans.substring_dedup(odd, with_text=False), licences.license_scan(odd), audio.audio_features(odd),
    ]
    ids = sorted((i for i, _ in rows), key=lambda i: (i is None, i))
    for frame in results:
        got = frame.collect()
        assert sorted((r["doc_id"] for r in got), key=lambda i: (i is None, i)) == ids, frame.columns
        twice = [r.asDict(True) for r in got if r["doc_id"] == 20]
        assert twice[0] == twice[1], frame.columns


def test_stages_equal_loops(spark, sf):
    import corpus_pipeline
    from curator.functions.workspace import stash

    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    scores = {r["doc_id"]: r["score"] for r in toxicity.toxicity(docs, spark.read.parquet(f"{sf}/labels.parquet")).collect()}
    docs = stash(stages["toxicity"](spark, docs, sf), "s")
    kept = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert set(kept) == {i for i, p in scores.items() if p < toxicity.THRESHOLD}

    docs = stash(stages["line dedup"](spark, docs, sf), "s")
    seen, want = set(), {}
    for i in sorted(kept):
        part, new, gone = [space(x) for x in kept[i].split("\n")], set(), set()
        for a in range(len(part)):
            size = 0
            for b in range(a + 1, len(part) + 1):
                size += len(part[b - 1])
                if size >= lines.MIN_WORDS:
                    block = hashlib.sha1(repr(part[a:b]).encode()).digest()
                    new.add(block)
                    gone |= set(range(a, b)) if block in seen else set()
        seen |= new
        left = [x for k, x in enumerate(part) if x and k not in gone]
        if left or not gone:
            want[i] = left
    kept = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert {i: [space(x) for x in t.split("\n") if space(x)] for i, t in kept.items()} == want

    docs = stash(stages["near dedup"](spark, docs, sf), "s")
    groups = brute_groups(list(kept.items()), 5)
    kept = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert set(kept) == {i for i, (_, top) in groups.items() if i == top}

    docs = stash(stages["decontamination"](spark, docs, sf), "s")
    windows = set()
    for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect():
        w = alnum(lower(r["text"]))
        n = min(13, len(w))
        windows |= {tuple(w[a : a + n]) for a in range(len(w) - n + 1 if n else 0)}
    sizes, clean = {len(x) for x in windows}, set()
    for i, t in kept.items():
        w, hit = alnum(lower(t)), set()
        for n in sizes:
            for a in range(len(w) - n + 1):
                if tuple(w[a : a + n]) in windows:
                    hit.update(range(a, a + n))
        clean |= {i} if not hit or 20 * len(hit) < len(w) else set()
    kept = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert set(kept) == clean

    lib = pieces.vocabulary(pieces.model_path()).lib
    for r in stages["encode and decode"](spark, docs, sf).collect():
        ids = lib.encode(kept[r["doc_id"]], add_bos=True, add_eos=True)
        assert r["ids"] == ids and r["decoded_sha256"] == hashlib.sha256(lib.decode(ids).encode()).hexdigest()


def test_stages_on_awkward_rows(spark, sf):
    """Null and empty texts are clean and unique; repeated rows stay together until one of each document is kept."""
    import corpus_pipeline

    text = "one two three four five six seven eight nine ten"
    rows = [(1, text), (1, text), (2, None), (2, None), (3, ""), (None, "a text without an id stands here"), (4, text)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    want = [
        rows, [*rows[:6]], [(1, text), (2, None), (3, ""), rows[5]], [(1, text), (2, None), (3, ""), rows[5]],
    ]
    order = lambda r: (r[0] is None, r[0] or 0, r[1] or "")
    for (name, stage), expected in zip(corpus_pipeline.STAGES[:-1], want, strict=True):
        docs = stage(spark, docs, sf)
        docs = spark.createDataFrame(docs.collect(), docs.schema)
        assert sorted(((r["doc_id"], r["text"]) for r in docs.collect()), key=order) == sorted(expected, key=order), name
        empty = spark.createDataFrame([], docs.schema)
        assert stage(spark, empty, sf).count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == 4
    assert zlib.crc32(b"1") % 4 != 2  # the first text may be learned from
