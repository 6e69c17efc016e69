"""Pipeline operators against brute force, exact round trips and awkward inputs."""

from __future__ import annotations

import hashlib
import io
import math
import re
import wave
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from curator.llm import audio, classlm, contamination, flat, licences, lines, near, pieces, spans, toxicity, unigram

SCHEMA = "doc_id long, text string, lang string, key string, n_words long"
BASE = "the quick brown fox jumps over the lazy dog and then runs far away from all the other animals of the old dark forest near town"
ROWS = [
    (3, BASE), (1, BASE + " again"), (2, BASE.upper()), (4, None), (5, ""), (6, " \n\t "), (7, "one"), (8, "One"), (9, "a b\nc d " * 30),
    (10, "é" * 40 + " \x00 ▁ 𝄞 <0x0A> ## " + BASE), (11, "x" * 5000), (12, "Licensed under CC BY-NC 4.0. All rights reserved."), (13, BASE + "\n" + BASE), (None, BASE), (14, "dup"), (14, "dup"), (14, "other text"),
]


def lower(text: str | None) -> str:
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def space(text: str) -> list[str]:
    return re.findall(r"[^\x20\x09-\x0D]+", text)


def alnum(text: str) -> list[str]:
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text)


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, None, "clash", -1) for i, t in ROWS], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def unique(spark):
    return spark.createDataFrame([(i, t, None, "clash", -1) for i, t in ROWS[:13]], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("rule, lowered", [("space", True), ("alnum", True), ("space", False)])
def test_flat_words(rule, lowered, monkeypatch):
    monkeypatch.setattr(flat, "CHUNK", 16)
    texts = [t for _, t in ROWS]
    find = space if rule == "space" else (lambda t: re.findall(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", t))
    seen: dict[str, int] = {}
    for i, j, w in flat.word_runs(pa.array(texts), rule, lowered, 64):
        for d in range(j - i):
            at = slice(w.first[d], w.first[d + 1])
            got = [bytes(w.data[a:b]).decode() for a, b in zip(w.starts[at], w.ends[at], strict=True)]
            assert got == find(texts[i + d] or "")
            for word, h in zip(got, w.hashes[at].tolist(), strict=True):
                assert seen.setdefault(lower(word) if lowered else word, h) == h
    assert len(set(seen.values())) == len(seen)


def brute_groups(rows: list, k: int) -> dict:
    sets = {}
    for i, t in rows:
        w = space(lower(t))
        sets[i] = {tuple(w[a : a + k]) for a in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    head = {i: i for i in sets}

    def top(x):
        while head[x] != x:
            x = head[x]
        return x

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 80 * len(sets[a] | sets[b]):
                p, q = top(a), top(b)
                head[max(p, q)] = min(p, q)
    return {i: (len(sets[i]), top(i)) for i in ids}


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates(spark, k):
    rng = np.random.default_rng(4)
    words = [f"w{i}" for i in range(300)]
    rows = list(ROWS[:13])
    for g in range(12):
        base = [words[x] for x in rng.integers(0, 300, 80)]
        for _ in range(int(rng.integers(1, 9))):
            new = list(base)
            for _ in range(int(rng.integers(0, 10))):
                new[int(rng.integers(0, 80))] = "edit"
            rows.append((100 + len(rows), " ".join(new)))
    want = brute_groups(rows, k)
    got = near.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), k).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == want
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_near_duplicates_awkward(odd, empty):
    got = near.near_duplicates(odd, 2).collect()
    assert len(got) == len(ROWS)
    assert near.near_duplicates(empty, 2).count() == 0


def test_odd_sketch_tells_similarity():
    rng = np.random.default_rng(2)
    a = rng.integers(1, 2**63, (50, 200), dtype=np.uint64)
    b = a.copy()
    b[:, 160:] = rng.integers(1, 2**63, (50, 40), dtype=np.uint64)
    far = np.bitwise_count(near.odd_sketches(a) ^ near.odd_sketches(b)).sum(axis=1)
    assert (far <= near.most_parity(200, 0.8)).all()
    none = np.bitwise_count(near.odd_sketches(a[:25]) ^ near.odd_sketches(a[25:])).sum(axis=1)
    assert (none > near.most_parity(200, 0.8)).all()


def brute_spans(rows: list, size: int) -> dict:
    seen, out = set(), {}
    for i, t in sorted(rows):
        w = space(t or "")
        gone = [False] * len(w)
        for a in range(len(w) - size + 1):
            key = tuple(w[a : a + size])
            if key in seen:
                gone[a : a + size] = [True] * size
            seen.add(key)
        out[i] = (len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone, strict=True) if not g).encode()).hexdigest())
    return out


@pytest.mark.parametrize("size", [3, 20])
def test_substring_dedup(unique, odd, empty, size):
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in spans.substring_dedup(unique, size, False).collect()}
    assert got == brute_spans(ROWS[:13], size)
    assert spans.substring_dedup(odd, size).count() == len(ROWS)
    assert spans.substring_dedup(empty, size).count() == 0


def test_contamination(spark, unique, odd, empty):
    items = [(1, BASE), (2, "the old dark"), (3, None), (4, ""), (5, "Lazy, dog!"), (12, "a b c d a b c d a b c d a b"), (12, "one"), (None, "dup")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    windows = defaultdict(set)
    for i, t in items:
        w = alnum(lower(t))
        n = min(13, len(w))
        for a in range(len(w) - n + 1 if n else 0):
            windows[tuple(w[a : a + n])].add(None if i is None else str(i))
    got = {r["doc_id"]: r for r in contamination.contamination(unique, bench).collect()}
    for i, t in ROWS[:13]:
        w, hit, found = alnum(lower(t)), set(), set()
        for key, ids in windows.items():
            for a in range(len(w) - len(key) + 1):
                if tuple(w[a : a + len(key)]) == key:
                    hit.update(range(a, a + len(key)))
                    found |= ids - {None}
        r = got[i]
        assert (r["n_words"], r["n_hit"], r["n_items"]) == (len(w), len(hit), len(found))
        assert r["items_sha256"] == hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
        assert r["contaminated"] == (bool(hit) and 20 * len(hit) >= len(w))
    assert contamination.contamination(odd, bench).count() == len(ROWS)
    assert contamination.contamination(empty, bench).count() == 0
    assert contamination.contamination(unique, bench.limit(0)).where("contaminated or n_hit > 0").count() == 0


def test_language_scores(spark, unique, odd, empty):
    docs = [(i, t) for i, t in ROWS[:13]] + [(100 + i, BASE + f" w{i % 7} v{i}") for i in range(60)]
    got = {r["doc_id"]: r for r in classlm.language_scores(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    tokens = {i: [*space(lower(t)), None] for i, t in docs}
    c = Counter(w for i in tokens if zlib.crc32(str(i).encode()) % 10 for w in tokens[i])
    n, v = sum(c.values()), len(c)
    for i, ws in tokens.items():
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(ws), sum(c[w] > 0 for w in ws), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws))
        assert math.isfinite(r["score"]) and r["score"] < 0 and r["held_out"] == (zlib.crc32(str(i).encode()) % 10 == 0)
    held = [r for r in got.values() if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)
    assert classlm.language_scores(odd).count() == len(ROWS)
    assert classlm.language_scores(empty).count() == 0


def test_exchange_finds_planted_classes():
    rng = np.random.default_rng(0)
    pairs = np.zeros((22, 22))
    for a in range(20):
        for b in range(20):
            pairs[a, b] = rng.poisson(30 if (a % 2) != (b % 2) else 1)
    of = classlm.exchange(pairs, 2)
    assert len(set(of[0:20:2])) == 1 and len(set(of[1:20:2])) == 1 and of[0] != of[1]


def test_pieces_equal_the_library(unique, odd, empty):
    v = pieces.vocabulary(pieces.model_path())
    rows = {r["doc_id"]: r for r in pieces.encode_decode(unique).collect()}
    for i, t in ROWS[:13]:
        want = v.lib.encode(t or "", add_bos=True, add_eos=True)
        assert rows[i]["ids"] == want and rows[i]["decoded"] == v.lib.decode(want) and rows[i]["n_tokens"] == len(want)
        assert rows[i]["ids_sha256"] == hashlib.sha256(np.array(want, dtype="<u4").tobytes()).hexdigest()
    assert pieces.encode_decode(odd).count() == len(ROWS) and pieces.encode_decode(empty).count() == 0


def test_unigram_equals_the_library(unique, empty):
    from tokenizers import Tokenizer, models

    u = unigram.unigram(pieces.model_path())
    low = min(u.scores.values())
    lib = Tokenizer(models.Unigram([("<unk>", low), *u.scores.items(), *[(f"<0x{b:02X}>", low) for b in range(256)]], 0, True))
    for r in unigram.token_counts(unique).collect():
        t = (dict(ROWS[:13])[r["doc_id"]] or "").replace("▁", " ")
        assert r["n_tokens"] == (len(lib.encode((" " + t).replace(" ", "▁")).ids) if t else 0)
    assert unigram.token_counts(empty).count() == 0


def test_toxicity(spark, odd, empty):
    rng = np.random.default_rng(1)
    rows = [(i, " ".join(f"w{x}" for x in rng.integers(0, 200, 30)) + (" idiot trash" if i % 4 == 0 else "")) for i in range(1200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i, _ in rows] + [(5000, 1), (None, 1), (3, None)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.toxicity(docs, labels).collect()}
    held = [i for i in got if zlib.crc32(str(i).encode()) % 4 == 2]
    assert all(got[i]["held_out"] for i in held) and sum(r["held_out"] for r in got.values()) == len(held)
    assert np.mean([got[i]["predicted"] == (i % 4 == 0) for i in held]) > 0.95
    assert len(toxicity.clean_documents(docs, labels).collect()) == sum(1 - r["predicted"] for r in got.values())
    scored = toxicity.toxicity(odd, labels).collect()
    assert len(scored) == len(ROWS) and all(0 <= r["score"] <= 1 for r in scored)
    assert toxicity.toxicity(empty, labels.limit(0)).count() == 0
    settings = [(1.0, 8.0, 1), (2.0, 8.0, 4)]
    compared = toxicity.compare_settings(docs, labels, settings).collect()
    assert sorted((r["alpha"], r["l1"], r["epochs"]) for r in compared) == settings and all(r["log_loss"] > 0 for r in compared)
    # rows of the held-out fold take no part in the choice
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    without = toxicity.compare_settings(docs.where(fold != 2), labels.where(fold != 2), settings).collect()
    assert sorted(without) == sorted(compared)


def test_licences(unique, empty):
    assert len(licences.rules()) >= 200
    got = {r["doc_id"]: r for r in licences.license_scan(unique).collect()}
    r = got[12]
    assert r["labels"] == "cc-by,cc-by-nc-4.0,reserved" and r["base_labels"] == "cc-by,reserved" and r["n_base"] == 2 and (r["first_word"], r["last_word"]) == (2, 7)
    for i, t in ROWS[:13]:
        assert got[i]["n_words"] == len(alnum(lower(t)))
    assert got[4]["first_word"] is None and got[4]["score"] == 0
    labels = lambda t: [x.label for _, _, x in licences.detections(t)]
    assert labels("GNU Lesser General Public License v2.1 or later") == ["lgpl-2.1-or-later"]
    assert labels("under the Apache License, Version 2.0") == ["apache-2.0"]
    assert licences.license_scan(empty).count() == 0


def test_audio(unique, empty):
    for r in audio.audio_features(unique).collect():
        raw = (dict(ROWS[:13])[r["doc_id"]] or "").encode()
        payload = raw + b"\0" * ((64 - len(raw) % 64) % 64 if raw else 64)
        assert (r["n_bytes"], r["payload_bytes"], r["tail_crc32"]) == (len(raw), len(payload), zlib.crc32(payload[-64:]))
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["media_sha256"] == hashlib.sha256(bytes(r["media"])).hexdigest()
        with wave.open(io.BytesIO(bytes(r["media"]))) as f:
            assert f.readframes(f.getnframes()) == payload
        assert audio.read_tensors(bytes(r["tensors"]))[0].shape == (len(r["spans"]), audio.TENSOR_FRAMES, audio.MELS)
    assert audio.audio_features(empty).count() == 0
    tone = np.sin(np.arange(4000) * 2 * np.pi * 440 / 16000).astype(np.float32)
    assert len(audio.resample(tone, 3, 4)) == 3000
    assert audio.segments(np.array([0.0, 5, 0.5, 0.2, 0, 5]), 0.0, 1.0, 0.3) == [(1, 3), (5, 6)]


def test_lines(spark, odd, empty):
    assert lines.patience([1, 2, 3, 4, 5], [9, 1, 2, 7, 4, 5]) == [(0, 1), (1, 2), (3, 4), (4, 5)]
    block = "this is a long enough line number one\nand here goes another long line of text\n"
    docs = spark.createDataFrame([(1, "start\n" + block + "end"), (2, "other\n" + block + "tail"), (3, "start\n" + block + "end"), (4, "nothing shared here at all")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in lines.line_dedup(docs).collect()}
    assert [got[i]["n_removed"] for i in (1, 2, 3, 4)] == [0, 2, 4, 0]
    assert got[2]["kept_text"] == "other\ntail" and got[1]["kept_text"] == "start\n" + block + "end"
    kept = {r["doc_id"]: r["text"] for r in lines.without_repeated_lines(docs).collect()}
    assert set(kept) == {1, 2, 4} and kept[2] == "other\ntail"
    assert lines.line_dedup(odd).count() == len(ROWS) and lines.line_dedup(empty).count() == 0
    assert lines.without_repeated_lines(empty).count() == 0


def test_short_lines_of_many_documents(spark):
    verse = "roses are red\nviolets are blue\nsugar is sweet"
    rows = [(i, f"own{i} text{i} of{i} document{i}\n{verse}\nend{i} of{i} it{i}") for i in range(80)]
    got = {r["doc_id"]: r["n_removed"] for r in lines.line_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: 3 if i else 0 for i in range(80)}


def test_repeated_and_moved_lines():
    assert lines.patience([1, 2, 2, 3, 9, 4], [1, 2, 2, 3, 8, 4]) == [(0, 0), (1, 1), (2, 2), (3, 3), (5, 5)]
    # 5 stands twice, but once in each gap
    assert lines.patience([1, 5, 2, 5, 3], [7, 1, 8, 5, 2, 9, 5, 3, 6]) == [(0, 1), (1, 3), (2, 4), (3, 6), (4, 7)]


def test_every_block_of_an_earlier_document_goes(spark):
    rng = np.random.default_rng(7)
    kinds = ["", "a", "b c", "d e f", "g h i j k", "l m n o p q r s t"]
    rows = [(i, "\n".join(kinds[x] for x in rng.integers(0, 6, int(rng.integers(1, 14))))) for i in range(60)]
    rows += [(100, "x1 y z\n" + kinds[5] + "\n" + kinds[5]), (101, "\n".join([kinds[5], "x2 y z", kinds[5], "x3 y z", kinds[5], kinds[5]]))]
    seen, want = set(), {}
    for i, t in rows:
        part, new = [x.split() for x in t.split("\n")], set()
        gone: set[int] = set()
        for a in range(len(part)):
            for b in range(a + 1, len(part) + 1):
                if sum(map(len, part[a:b])) >= lines.MIN_WORDS:
                    block = tuple(map(tuple, part[a:b]))
                    new.add(block)
                    gone |= set(range(a, b)) if block in seen else set()
        seen |= new
        want[i] = "\n".join(" ".join(x) for k, x in enumerate(part) if x and k not in gone)
    got = lines.line_dedup(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert {r["doc_id"]: "\n".join(x for x in r["kept_text"].split("\n") if x) for r in got} == want


def sample(tree, k: int) -> str:
    """A string of a parsed regex; k chooses among alternatives."""
    out = ""
    for kind, value in tree:
        name = str(kind)
        if name == "LITERAL":
            out += chr(value)
        elif name == "IN":
            sort, what = value[k % len(value)]
            out += chr(what) if str(sort) == "LITERAL" else {"CATEGORY_SPACE": " ", "CATEGORY_DIGIT": "7"}.get(str(what), "x")
        elif name == "BRANCH":
            out += sample(value[1][k % len(value[1])], k // len(value[1]))
        elif name == "SUBPATTERN":
            out += sample(value[3], k)
        elif name == "MAX_REPEAT":
            out += sample(value[2], k) * max(value[0], k % 2)
    return out


def test_licence_gates_drop_no_match():
    compiled = 0
    for rule in licences.rules():
        regex = re.compile(rule.pattern)
        texts = {sample(licences.parser.parse(rule.pattern), k) for k in range(24)}
        texts = {t for t in texts if regex.search(t)}
        compiled += bool(texts)
        for t in texts:
            assert licences.detections(t) == licences.detections(t, gated=False) != []
    assert compiled > 300


@pytest.mark.parametrize(
    "text, label",
    [
        ("GPLv2", "gpl-2"), ("GPLv3+", "gpl-3-or-later"), ("LGPLv2.1", "lgpl-2.1"), ("AGPLv3", "agpl-3"), ("MIT licence", "mit"), ("Expat License", "mit"), ("do what the heck you want to public license", "wtfpl"),
        ("beer-ware", "beerware"), ("(c) 2020", "copyright"), ("©2020", "copyright"),
    ],
)
def test_licence_spellings(text, label):
    assert [x.label for _, _, x in licences.detections(text)] == [label]
