"""Operators of the method against plain loops."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from curator.functions.keyed import draw
from curator.functions.text import n_tokens
from curator.operators import baselines, embed, hygiene, lloyd, measures, probes, refine, sampling, theory
from curator.operators.features import cluster_features, levels


def unit_rows(rng, n, d):
    x = rng.normal(size=(n, d))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_draws_of_purposes_are_independent(spark):
    ids = spark.range(20_000).withColumnRenamed("id", "doc_id")
    p, t = draw("doc_id", 42, "probe") < 0.2, draw("doc_id", 42, "take") < 0.3
    n, probe, taken, both = ids.agg(F.count(F.lit(1)), *[F.sum(c.cast("int")) for c in (p, t, p & t)]).first()
    assert probe / n == pytest.approx(0.2, abs=0.01) and taken / n == pytest.approx(0.3, abs=0.01) and both / n == pytest.approx(0.06, abs=0.007)
    with pytest.raises(ValueError):
        sampling.Budget(tokens=5).unit("docs")
    assert sampling.Budget(docs=5).unit() == "docs" and sampling.Budget(fraction=0.5).unit("docs") == "docs" and sampling.Budget(tokens=5).unit() == "tokens"


def grams(text, n):
    w = text.lower().split()
    return {tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def test_near_copies_equal_brute_force(spark):
    rng, words = np.random.default_rng(11), [f"w{i}" for i in range(90)]
    rows = []
    for _ in range(5):
        chain = list(rng.permutation(words))
        for _ in range(int(rng.integers(2, 12))):
            rows.append((len(rows), " ".join(chain)))
            chain[int(rng.integers(0, 90))] = f"e{int(rng.integers(0, 9))}"
            chain[int(rng.integers(80, 90))] = "e"
    sets, head = [grams(t, 5) for _, t in rows], list(range(len(rows)))
    for a in range(len(rows)):
        for b in range(a):
            if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                x, y = head[a], head[b]
                head = [min(x, y) if h in (x, y) else h for h in head]
    kept = hygiene.dedup_near(spark.createDataFrame(rows, "doc_id long, text string").repartition(3))
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(head))


def test_decontamination_by_minhash(spark):
    text = " ".join(f"w{i}" for i in range(60))
    docs = spark.createDataFrame([(1, text + " end"), (2, "nothing of that sort is in here"), (3, None)], "doc_id long, text string")
    bench = spark.createDataFrame([("a", text), ("b", text), ("c", "other words stand here")], "item_id string, text string")
    kept, audit = hygiene.decontaminate(docs, bench, mode="minhash")
    assert sorted(r["doc_id"] for r in kept.collect()) == [2, 3]
    assert sorted((r["doc_id"], r["item_id"], round(r["overlap"], 4)) for r in audit.collect()) == [(1, "a", round(58 / 59, 4)), (1, "b", round(58 / 59, 4))]


def test_contains_finds_substrings(spark):
    docs = [(1, "say the quick brown fox jumps over it"), (2, "he quick brown fox jumps ove"), (3, "fox"), (4, None), (5, "xfoxy and\nmore")]
    items = [("a", "he quick brown fox jumps ove"), ("b", "fox"), ("c", "xy and\nmo"), ("d", None), ("e", "the slow brown fox")]
    got = hygiene.contains(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id string, text string")).distinct().collect()
    assert {(r[0], r[1]) for r in got} == {(i, k) for i, t in docs for k, x in items if t and x and x in t}


def test_equal_ratings(spark):
    rows = [(i, 10, 0.5 if i % 7 else 0.9) for i in range(300)]
    got = baselines.rating_selector(spark.createDataFrame(rows, "doc_id long, n_tokens long, rating double").repartition(4), 1005)
    assert sorted(r["doc_id"] for r in got.collect()) == sorted(i for i, _, _ in sorted(rows, key=lambda r: (-r[2], r[0]))[:100])


def test_shared_scans_fit_the_same_sub_clusters(spark):
    x = unit_rows(np.random.default_rng(2), 240, 6)
    rows = spark.createDataFrame([(i, i % 2, v.tolist(), 0.0) for i, v in enumerate(x)], "doc_id long, k int, emb array<double>, dist double").repartition(3)
    counts = refine.sub_counts(rows.groupBy("k").agg(F.count(F.lit(1)).alias("n")), 0.5)
    one = {r["doc_id"]: (r["j"], r["dist_sub"]) for r in refine.subcluster(rows, counts, iters=4).collect()}
    many = {r["doc_id"]: (r["j"], r["dist_sub"]) for r in refine.subcluster(rows, counts, iters=4, rows_per_task=40).collect()}
    assert {i: j for i, (j, _) in one.items()} == {i: j for i, (j, _) in many.items()}
    assert all(one[i][1] == pytest.approx(many[i][1]) for i in one)


def test_plain_distances_and_empty_clusters(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(120, 5)) * 3
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "doc_id long, emb array<double>").repartition(3)
    mu = x[:4].copy()
    new, _ = lloyd.step(df, {4: mu}, "l2")
    near = ((x[:, None] - mu[None]) ** 2).sum(2).argmin(1)
    assert np.allclose(new[4], [x[near == k].mean(0) for k in range(4)])
    y = unit_rows(rng, 50, 5)
    same = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(y)], "doc_id long, emb array<double>")
    start = np.array([y[0], y[0], y[1]])
    new, _ = lloyd.step(same, {3: start})
    dist = np.sqrt(((y[:, None] - start[None]) ** 2).sum(2)).min(1)
    assert np.allclose(new[3][1], y[dist.argmax()])


def test_one_scan_assigns_every_resolution(spark):
    x = unit_rows(np.random.default_rng(6), 60, 4)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "doc_id long, emb array<double>").repartition(2)
    centres = {2: x[:2], 5: x[:5]}
    got = {(r["resolution"], r["doc_id"]): r["k"] for r in lloyd.assign_all(df, centres, ("doc_id",)).collect()}
    assert got == {(r, i): int(np.argmax(np.round(x[i] @ mu.T, 12))) for r, mu in centres.items() for i in range(60)}


def test_hashed_text_equals_loops(spark, monkeypatch):
    texts = ["Some text, some TEXT", "", None, "ab", "a longer line of text " * 20, "é" * 9]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(2)
    odd = [int(v) | 1 for v in np.random.default_rng(42).integers(1, 1 << 62, 5)]
    for r in embed.hashed_text(df, 8).collect():
        b, want = (texts[r["doc_id"]] or "").lower().encode(), np.zeros(8)
        for n in (3, 4, 5):
            seen: dict[int, int] = {}
            for i in range(len(b) - n + 1):
                h = 0
                for k in range(n):
                    h = (h + b[i + k] + 1) * odd[k] % 2**64
                h ^= h >> 29
                h = h * 0xBF58476D1CE4E5B9 % 2**64
                h ^= h >> 32
                seen[h] = seen.get(h, 0) + 1
            for h, c in seen.items():
                want[h % 8] += np.log1p(c) * (1 if h >> 63 else -1)
        length = np.linalg.norm(want)
        assert np.allclose(r["emb"], want / length if length else want)


def test_vectors_from_a_column_and_a_model(spark):
    df = spark.createDataFrame([(1, [3.0, 4.0], "a b"), (2, [0.0, 0.0], None)], "doc_id long, embedding array<double>, text string")
    assert [r["emb"] for r in embed.from_column(df, d=2).orderBy("doc_id").collect()] == [pytest.approx([0.6, 0.8]), [0.0, 0.0]]
    got = embed.with_model(df, lambda: lambda ts: np.array([[len(t), 0.0] for t in ts])).orderBy("doc_id").collect()
    assert [r["emb"] for r in got] == [[1.0, 0.0], [0.0, 0.0]]
    probe = df.select(F.lit(0).alias("k"), "doc_id")
    assert probes.score_with(probe, df, lambda: lambda ts: [len(t) / 10 for t in ts], ("k",)).first()["p"] == pytest.approx(0.15)


def test_levels_and_declared_tables(spark, tmp_path):
    from curator.sources import tables

    rows = spark.createDataFrame([(0, 0, "a", 5, 0.1, 0.2), (0, 1, "b", 7, 0.3, 0.4), (1, 0, "a", 9, 0.5, 0.6)], "k int, j int, lang string, n_tokens long, dist_sub double, dist double")
    got = {(r["gid"], r["k"], r["j"]): r["n"] for r in levels(rows).collect()}
    assert got == {(0, 0, 0): 1, (0, 0, 1): 1, (0, 1, 0): 1, (1, 0, None): 2, (1, 1, None): 1, (3, None, None): 3}
    with pytest.raises(ValueError):
        tables.validated(rows, tables.DOCUMENTS)
    tables.write_small(cluster_features(rows, ["k"]), str(tmp_path / "small"))
    assert spark.read.json(str(tmp_path / "small")).count() == 2


def test_entropy_at_parts_is_that_of_the_prefix(spark):
    docs = spark.createDataFrame([(i, "a b c " * (i % 3 + 1) + f"w{i % 5}") for i in range(60)], "doc_id long, text string")
    held = spark.createDataFrame([("x", "a w1 new"), ("y", "b c w3")], "lang string, text string")
    got = {(r["part"], r["lang"]): r["value"] for r in measures.cross_entropy_at(docs, held, (0.3, 1.0, 0.6), 64).collect()}
    for part in (0.3, 0.6, 1.0):
        for r in measures.cross_entropy(sampling.epoch_prefix(docs, part), held, 64).collect():
            assert got[part, r["lang"]] == pytest.approx(r["value"])


def test_sliced_cost_is_at_most_the_exact_one(spark):
    rng = np.random.default_rng(8)
    x, y = rng.normal(size=(40, 3)), rng.normal(size=(40, 3)) + 1.5
    a, b = (spark.createDataFrame([(v.tolist(),) for v in m], "emb array<double>") for m in (x, y))
    even = np.full(40, 1 / 40)
    sliced = theory.w2_sliced(a, b, 96, 40, 3).first()[0]
    assert 0 < sliced <= 1.1 * theory.w2_exact(x, even, y, even)


def test_weights_on_the_driver_equal_those_of_the_table(spark):
    from curator.operators import consensus

    zn = {f: np.random.default_rng(i).normal(size=9) for i, f in enumerate(consensus.FEATURES)}
    table = spark.createDataFrame([(k, *(float(zn[f][k]) for f in consensus.FEATURES)) for k in range(9)], "k int, " + ", ".join(f"zn_{f} double" for f in consensus.FEATURES))
    for how, kind in (("spectral", "shifted"), ("power", "relu"), ("uniform", "abs")):
        assert consensus.weights_of(zn, how, kind) == pytest.approx(consensus.weights(table, how, kind))


def test_grams_are_hashed_once(spark):
    texts = ["A b c d", "a B", "", None, " \t\n", "x y z x y z x y"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame([("i", "a b c e f"), ("j", "A b"), ("k", " "), ("l", "y z x y z")], "item_id string, text string")
    got = {(r["doc_id"], r["item_id"], round(r["overlap"], 6)) for r in hygiene.overlap(docs, bench, 3).collect()}
    assert got == {(0, "i", round(1 / 3, 6)), (1, "j", 1.0), (5, "l", 1.0)}
    assert {r["doc_id"] for r in hygiene._gram_sets(docs, "doc_id", 3).collect()} == {0, 1, 5}
    # no inferred filter that makes a text's words again for each of its grams
    plan = hygiene._gram_hashes(docs, "doc_id", 8)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("regexp_extract_all") == 1


def test_hashed_vectors_against_loops_and_time():
    import time

    import pyarrow as pa

    texts = ["abcab", "", None, "ab", "aaaa", "é" * 9]
    odd = [int(x) | 1 for x in np.random.default_rng(42).integers(1, 1 << 62, 5)]
    want = np.zeros((len(texts), 8))
    for i, text in enumerate(texts):
        data, counts = (text or "").encode(), {}
        for n in range(3, 6):
            for a in range(len(data) - n + 1):
                h = 0
                for k in range(n):
                    h = (h + data[a + k] + 1) * odd[k] % 2**64
                h ^= h >> 29
                h = h * 0xBF58476D1CE4E5B9 % 2**64
                h ^= h >> 32
                counts[n, h] = counts.get((n, h), 0) + 1
        for (_, h), c in counts.items():
            want[i, h % 8] += np.log1p(c) * (1 if h >> 63 else -1)
        want[i] /= np.linalg.norm(want[i]) or 1.0
    run = embed._hashed(8, (3, 5), 42)
    got = next(run(iter([pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts)], names=["doc_id", "text"])])))
    assert np.allclose(np.array(got["emb"].flatten()).reshape(-1, 8), want)
    # less than two sorts of all hashes by two keys; three such sorts took most of the time before
    rng = np.random.default_rng(1)
    long = ["".join(map(chr, rng.integers(97, 123, 4000))) for _ in range(250)]
    began = time.process_time()
    for n in range(2):
        np.lexsort((rng.integers(0, 1 << 62, 1_000_000), np.repeat(np.arange(250), 4000)))
    sort = time.process_time() - began
    began = time.process_time()
    list(run(iter([pa.RecordBatch.from_arrays([pa.array(range(250)), pa.array(long)], names=["doc_id", "text"])])))
    assert time.process_time() - began < sort


def test_published_avg_reads_lineitem(spark, sf):
    import duckdb

    import __spark_entry__ as entry

    df = entry.queries()["published_avg"](spark, sf)
    assert any(f.endswith("lineitem.parquet") for f in df.inputFiles())
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{sf}/lineitem.parquet'")
    got, want = sorted(tuple(r) for r in df.collect()), sorted(con.sql(entry.oracle_sql()["published_avg"]).fetchall())
    assert got == want and {r[6] for r in got if r[1] == "N"} == {"same"} and len(got) > 3


def test_measures_of_many_subsets_are_those_of_each(spark):
    docs = spark.createDataFrame([(i, "abc"[i % 3], "st"[i % 2], None if i == 7 else " ".join(f"W{(i * j) % 11}" for j in range(i))) for i in range(30)], "doc_id long, lang string, source string, text string")
    held = docs.where("doc_id % 4 = 1")
    labels = spark.createDataFrame([(i, i % 2, int(i % 5 == 0)) for i in range(0, 30, 2)], "doc_id long, quality int, toxic int")
    cells = docs.select("doc_id", (F.col("doc_id") % 4).alias("k"))
    subsets = [docs.where(w).select("doc_id") for w in ("doc_id % 2 = 0", "lang = 'a'", "false", "doc_id = 7", "true")]
    owners, n = measures.members(subsets), len(subsets)

    def rows(df, *keys):
        return {tuple(r[k] for k in keys): tuple(v for c, v in r.asDict().items() if c not in ("i", "buckets", *keys)) for r in df.collect()}

    entropy = rows(measures.cross_entropies(docs, owners, n, held, (64, 128)), "buckets", "i", "lang")
    cover, tokens, quality = rows(measures.coverages(cells, owners, n), "i"), rows(measures.token_shares(docs, owners, n), "i", "lang"), rows(measures.qualities(labels, owners, n), "i")
    for i, ids in enumerate(subsets):
        chosen = docs.join(ids, "doc_id", "left_semi")
        for b in (64, 128):
            for (lang,), (value,) in rows(measures.cross_entropy(chosen, held, b), "lang").items():
                assert entropy[b, i, lang][0] == pytest.approx(value)
        assert cover[i,] == pytest.approx(tuple(measures.coverage(cells, ids).first()), nan_ok=True)
        alone = chosen.groupBy("lang").agg(F.sum(n_tokens("text")).cast("double").alias("v"))
        assert {lang: v for (j, lang), v in tokens.items() if j == i} == {r["lang"]: (r["v"],) for r in alone.collect()}
        assert quality[i,][0] == labels.join(ids, "doc_id", "left_semi").agg(F.avg(F.col("quality") * (1 - F.col("toxic")))).first()[0]
    assert len(entropy) == 2 * n * 3


def test_step_sends_one_matrix_for_each_merger(spark):
    rng = np.random.default_rng(4)
    x = unit_rows(rng, 400, 5)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "doc_id long, emb array<double>").repartition(23)
    got, cost = lloyd.step(df, {3: x[:3], 7: x[:7]})
    for r in (3, 7):
        k = np.argmax(x @ x[:r].T, axis=1)
        mean = np.array([x[k == j].mean(axis=0) for j in range(r)])
        assert np.allclose(got[r], mean / np.linalg.norm(mean, axis=1, keepdims=True))
        assert cost[r] == pytest.approx(np.linalg.norm(x - x[:r][k], axis=1).mean())
    parts = df.select("emb").mapInArrow(lloyd._partial_sums(spark.sparkContext.broadcast({3: x[:3]}), "cosine"), lloyd.PARTIAL).repartition(lloyd.MERGERS).mapInArrow(lloyd._merged, lloyd.PARTIAL)
    assert parts.count() <= lloyd.MERGERS


def test_texts_that_share_no_words_with_an_item_are_sifted_out(spark):
    rng = np.random.default_rng(5)
    texts = [" ".join(rng.choice(list("abcé"), rng.integers(0, 12))) for _ in range(80)] + ["a  b\tc\fa\r\nb", "", None, " ", "é", "ab c a b"]
    items = ["c a b é a", "É", "a b", "", None]
    rows = lambda t, n: {tuple(w[i : i + n]) for w in [t.split()] for i in range(max(len(w) - n + 1, min(len(w), 1)))}
    docs = spark.createDataFrame([(i, t and t.lower()) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    bench = spark.createDataFrame([(t and t.lower(),) for t in items], "text string")
    for n in (1, 2, 4, 70):
        wanted = {r for t in items if t for r in rows(t.lower(), n)}
        got = {r["doc_id"] for r in hygiene._meeting(docs, bench, n).collect()}
        assert got == {i for i, t in enumerate(texts) if t and rows(t.lower(), n) & wanted}
    # texts in a row don't run into each other, and a sift of more marks than a task may hold leaves all
    data = np.frombuffer(b"a bc d", dtype=np.uint8)
    together, apart = hygiene._row_marks(data, np.array([0, 6]), 2), hygiene._row_marks(data, np.array([0, 3, 3, 6]), 2)
    assert together[0].tolist() == [0, 0] and apart[0].tolist() == [0, 2] and together[1][0] != apart[1][0]


def test_too_many_marks_leave_all_texts(spark, monkeypatch):
    docs, bench = spark.createDataFrame([(1, "x"), (2, "a b")], "doc_id long, text string"), spark.createDataFrame([("a b c",)], "text string")
    assert hygiene._meeting(docs, bench, 2).count() == 1
    monkeypatch.setattr(hygiene, "MARKS", 1)
    assert hygiene._meeting(docs, bench, 2).count() == 2
