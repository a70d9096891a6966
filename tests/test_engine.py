"""Toys with known answers, the planted experiment's known figures, and properties of plans, codebooks, poses and streams."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqsearch.config import CodebookParams, MetricParams, ModelParams
from seqsearch.functions.autodiff import Node
from seqsearch.operators import encoder, histogram, index, onepass, periodicity, quantize, relational, training
from seqsearch.operators.shortlist import shortlist, shortlist_size
from seqsearch.plans import evaluate, retrieve
from seqsearch.schemas import CODEBOOK, PATCH, SEQ, validate
from seqsearch.sources import io, pose, tokens

SF = "/root/testdata/sf0.01"


def sequences(spark, rows, classes=None):
    made = [(i, (classes or {}).get(i, str(i)), 0, list(r), None, len(r)) for i, r in enumerate(rows)]
    return spark.createDataFrame(made, SEQ)


def test_shortlist_sizes():
    want = {0: (0, 0), 1: (1, 1), 50: (50, 50), 200: (200, 200), 399: (200, 200), 402: (201, 200), 500: (250, 200), 1400: (700, 200), 5000: (2500, 200)}
    assert {n: (shortlist_size(n, "printed"), shortlist_size(n, "capped")) for n in want} == want


def test_periodicity_toys(spark):
    rows = [[1, 2, 3] * 6, [1, 9] * 5, [1, 2, 3, 4, 5, 6], [4] * 8, [], [7]]
    got = {r["seq_id"]: (r["peaks"], r["is_periodic"]) for r in periodicity.periodicity(sequences(spark, rows)).collect()}
    assert got[0] == ([3, 6], True) and got[1] == ([2], False)
    assert all(got[k] == ([], False) for k in (2, 3, 4, 5))
    assert periodicity.dominant_period(periodicity.periodicity(sequences(spark, rows))).where("seq_id = 0").first()["period"] == 3


def test_evaluation_toy(spark):
    cls = {i: "a" if i < 5 else "b" for i in range(10)}
    ranked = [(0, 1, 1, 1.0), (1, 1, 5, 1.0), (1, 2, 2, 0.9), (2, 1, 5, 1.0), (2, 2, 6, 0.9), (2, 3, 3, 0.8), (3, 1, 5, 1.0)]
    seq = sequences(spark, [[0]] * 10, cls)
    scores = evaluate.query_scores(spark.createDataFrame(ranked, "query_id long, rank int, cand_id long, score double"), seq)
    m = evaluate.measures(scores, "toy").first()
    assert (m["mean_score"], m["match_rate"], m["rank1_rate"], m["queries"]) == (0.4375, 75.0, 25.0, 4)
    assert m["rank_hist"] == {"1": 1, "2": 1, "3": 1, "none": 1}
    three = sequences(spark, [[0]] * 15, {i: str(i % 3) for i in range(15)})
    refs, queries = evaluate.leave_k_out(three, 2)
    assert (refs.count(), queries.count()) == (6, 9)


@pytest.mark.parametrize("noise,want", [(30, {"histogram": 0.260, 10: 0.660, 20: 0.787, 50: 0.870, "exhaustive": 0.875}), (50, {"histogram": 0.048, "exhaustive": 0.297})])
def test_planted_experiment(spark, noise, want):
    """Twenty users, five noisy instances, their first 32 events: figures known from an independent script."""
    users = tokens.event_tokens(io.read_table(spark, SF, "events")).where("seq_id < 20")
    first = users.withColumn("tokens", F.slice("tokens", 1, 32)).withColumn("times", F.slice("times", 1, 32)).withColumn("len", F.size("tokens"))
    seq = tokens.perturb(first, 5, noise).withColumn("times", F.lit(None).cast("array<double>")).persist()
    made = {"histogram": lambda: retrieve.retrieve_histogram(seq, seq), "exhaustive": lambda: retrieve.retrieve_exhaustive(seq, seq)}
    for k, mean in want.items():
        answers = made[k]() if k in made else retrieve.retrieve(seq, seq, retrieve.RetrievalPlan(policy="capped", cap=k))
        got = evaluate.measures(evaluate.query_scores(answers, seq, seq), str(k)).first()["mean_score"]
        assert abs(got - mean) < 0.0011, (k, got)


def test_bounded_equals_exhaustive_and_recall_grows(spark):
    seq = tokens.event_tokens(io.read_table(spark, "/root/testdata/sf0.001", "events")).persist()
    rows = lambda df: sorted((r["query_id"], r["rank"], r["cand_id"]) for r in df.collect())
    full = retrieve.retrieve_exhaustive(seq, seq)
    assert rows(full) == rows(retrieve.retrieve_bounded(seq, seq)) == rows(retrieve.retrieve(seq, seq))
    recall = [evaluate.shortlist_recall(shortlist(seq, seq, "fixed", n), full).first()["recall"] for n in (3, 6, 12)]
    assert recall == sorted(recall)


def test_histogram_properties(spark):
    rows = [[1, 2, 2, 3], [2, 3, 1, 2], [1, 2, 2, 3] * 2, [], [9]]
    seq = sequences(spark, rows)
    pairs = {(r["query_id"], r["cand_id"]): r["cosine"] for r in histogram.cosine_pairs(seq, seq).collect()}
    assert abs(pairs[0, 1] - 1) < 1e-12 and abs(pairs[0, 2] - 1) < 1e-12 and (0, 4) not in pairs
    assert {r["seq_id"]: r["n"] for r in seq.select("seq_id", histogram.norm_of("tokens").alias("n")).collect()} == {0: 6, 1: 6, 2: 24, 3: 0, 4: 1}
    short = shortlist(seq, seq, "fixed", 4)
    assert short.groupBy("query_id").count().where("count <> 4").count() == 0


def test_index(spark, tmp_path):
    seq = sequences(spark, [[1, 2], [2, 3], [3]])
    path = str(tmp_path / "index")
    index.build_index(seq.where("seq_id < 2"), path)
    assert index.merge_index(spark, path, seq) == 1 and index.merge_index(spark, path, seq) == 0
    index.remove_from_index(spark, path, seq.where("seq_id = 1"))
    postings, rows = index.read_index(spark, path)
    assert sorted((r["seq_id"], r["word"]) for r in postings.collect()) == [(0, 1), (0, 2), (2, 3)] and rows.count() == 2
    index.compact_index(spark, path, str(tmp_path / "new"))
    assert index.read_index(spark, str(tmp_path / "new"))[0].count() == 3
    assert index.read_index(spark, str(tmp_path / "none"))[0].count() == 0


@pytest.mark.parametrize("where", ["postings", "commit"])
def test_a_crash_within_a_merge(spark, tmp_path, monkeypatch, where):
    """A batch that is cut short between its two tables, or before its commit, is not seen, and its replay counts once."""
    path = str(tmp_path / "index")
    index.build_index(sequences(spark, [[1, 2], [2, 3]]), path)
    before = sorted(map(tuple, index.read_index(spark, path)[0].collect()))
    new = sequences(spark, [[1], [2], [5, 5, 6]])

    def crash(*_):
        raise RuntimeError("executor lost")

    with monkeypatch.context() as m:
        m.setattr(index, "word_counts" if where == "postings" else "_commit", crash)
        with pytest.raises(RuntimeError):
            index.merge_index(spark, path, new, batch="b7")
    assert sorted(map(tuple, index.read_index(spark, path)[0].collect())) == before
    for _ in range(2):
        index.merge_index(spark, path, new, batch="b7")
        assert sorted(map(tuple, index.read_index(spark, path)[0].collect())) == sorted([*before, (2, 5, 2), (2, 6, 1)])


def test_retriever_answers_like_a_table(spark, tmp_path):
    seq = tokens.event_tokens(io.read_table(spark, "/root/testdata/sf0.001", "events"), 8)
    path = str(tmp_path / "index")
    index.build_index(seq.where("seq_id % 2 = 1"), path)
    index.merge_index(spark, path, seq)
    stored = index.Retriever(spark, path).persist()
    rows = lambda df: sorted((r["query_id"], r["rank"], r["cand_id"]) for r in df.collect())
    plan = retrieve.RetrievalPlan(policy="capped", cap=5)
    for some in (seq.where("seq_id < 3"), seq.where("seq_id >= 3")):
        assert rows(stored.retrieve(some, plan)) == rows(retrieve.retrieve(some, seq, plan))
    assert stored.size() == seq.count()
    stored.unpersist()


def test_many_queries_take_the_joins(spark, monkeypatch, tmp_path):
    """Beyond the broadcast bound the joins of postings and pairs give the same answers."""
    seq = tokens.event_tokens(io.read_table(spark, "/root/testdata/sf0.001", "events")).persist()
    path = str(tmp_path / "index")
    index.build_index(seq, path)
    vectors = io.read_table(spark, "/root/testdata/sf0.001", "embeddings")
    rows = lambda df: sorted((r["query_id"], r["rank"], r["cand_id"], round(r["score"], 9)) for r in df.collect())
    runs = [
        lambda: retrieve.retrieve_exhaustive(seq, seq), lambda: retrieve.retrieve_bounded(seq, seq), lambda: retrieve.retrieve_histogram(seq, seq), lambda: retrieve.retrieve(seq, seq),
        lambda: retrieve.retrieve(seq, seq, retrieve.RetrievalPlan(policy="capped", cap=4, timed=True)), lambda: retrieve.retrieve_exhaustive(seq, seq, retrieve.RetrievalPlan(timed=True)),
        lambda: index.Retriever(spark, path).retrieve(seq, retrieve.RetrievalPlan(policy="capped", cap=4)), lambda: retrieve.retrieve_embedding(vectors.where("vec_id < 40"), vectors),
    ]
    near = [rows(r()) for r in runs]
    monkeypatch.setattr(onepass, "MOST_QUERIES", 0)
    assert [rows(r()) for r in runs] == near and all(near)


def test_odd_sequences_in_one_pass(spark):
    """Empty, single and unknown tokens; every plan against all pairs."""
    seq = sequences(spark, [[], [0], [1, 1, 1], [1, 2, 3, 4, 5, 6], [6, 5, 4, 3, 2, 1], [999], [1, 2, 3, 4, 5, 7], []])
    rows = lambda df: sorted((r["query_id"], r["rank"], r["cand_id"], round(r["score"], 9)) for r in df.collect())
    few = seq.where("seq_id in (0, 2, 3, 5)")
    for plan in (retrieve.RetrievalPlan(), retrieve.RetrievalPlan(weights={"edr": 0.5, "twed": 0.5}, exclude_self=False), retrieve.RetrievalPlan(weights={"lcss": 0.4, "dtw": 0.2, "ngram": 0.4}, params=MetricParams(ngram=3, twed="original"))):
        want = rows(retrieve._answer(retrieve.score_pairs(retrieve.all_pairs(few, seq, plan.exclude_self), few, seq, plan), plan.k))
        assert rows(retrieve.retrieve_exhaustive(few, seq, plan)) == want == rows(retrieve.retrieve_bounded(few, seq, plan))


def test_bounded_aligns_less(spark):
    users = tokens.event_tokens(io.read_table(spark, "/root/testdata/sf0.001", "events"))
    seq = tokens.perturb(users, 4, 10).persist()
    c = retrieve.pruning_counters(seq, seq).first()
    assert c["pairs"] == seq.count() * (seq.count() - 1) and c["cells"] < 0.6 * c["all_cells"]


def test_quantiser_toy(spark):
    patches = spark.createDataFrame([(0, 0, [0.0, 0.0]), (0, 1, [0.0, 1.0]), (0, 2, [4.0, 4.0])], PATCH)
    book = spark.createDataFrame([(k, [v, v], 1.0, [v, v], 0) for k, v in ((0, 0.0), (1, 5.0), (2, 9.0))], CODEBOOK)
    for how in ("native", "arrow"):
        got = sorted((r["patch_idx"], r["code"], r["dist2"]) for r in quantize.assign(patches, book, how).collect())
        assert got == [(0, 0, 0.0), (1, 0, 1.0), (2, 1, 2.0)]
    found = quantize.assign(patches, book)
    new = {r["code"]: r for r in quantize.ema_step(book, quantize.code_sums(patches, found)).collect()}
    assert [new[k]["ema_n"] for k in range(3)] == [1.5, 1.0, 0.5]
    assert np.allclose([new[k]["centroid"] for k in range(3)], [[0, 1 / 3], [4.5, 4.5], [9, 9]])
    assert abs(quantize.usage(found, 3).first()["usage"] - 66.666667) < 1e-5
    assert abs(quantize.code_entropy(found).first()["entropy"] - (math.log(3) - 2 / 3 * math.log(2))) < 1e-9
    assert quantize.commitment_loss(found).first()["loss"] == 1.0
    alive = {r["code"]: r for r in quantize.revive(book, found, patches).collect()}
    assert alive[2]["centroid"] in ([0.0, 0.0], [0.0, 1.0], [4.0, 4.0]) and alive[0]["centroid"] == [0.0, 0.0]


def test_revival_helps(spark):
    e = io.read_table(spark, SF, "embeddings")
    lat = e.select(F.floor(F.col("vec_id") / 20).alias("clip_id"), (F.col("vec_id") % 20).cast("int").alias("t"), F.col("embedding").alias("latent"))
    patches = quantize.patchify(lat, 2).persist()
    start = quantize.initial_codebook(patches, 128, collapsed=True)
    last = {}
    for revive in (False, True):
        _, h = quantize.fit_codebook(patches, CodebookParams(codes=128, revive=revive, epochs=5), start)
        last[revive] = h[-1]
    assert last[True]["usage"] > 80 and last[True]["error"] < last[False]["error"] and last[True]["usage"] >= last[False]["usage"]


def test_fused_epoch_equals_its_parts(spark):
    e = io.read_table(spark, "/root/testdata/sf0.001", "embeddings")
    lat = e.select(F.floor(F.col("vec_id") / 20).alias("clip_id"), (F.col("vec_id") % 20).cast("int").alias("t"), F.col("embedding").alias("latent"))
    patches = quantize.patchify(lat, 2)
    book = quantize.initial_codebook(patches, 32)
    found = quantize.assign(patches, book, "arrow")
    want = {r["code"]: (r["hits"], r["total"]) for r in quantize.code_sums(patches, found).collect()}
    got = {r["code"]: r for r in quantize.epoch_sums(patches.repartition(5), book).collect()}
    assert {k: r["hits"] for k, r in got.items()} == {k: v[0] for k, v in want.items()}
    assert all(np.allclose(got[k]["total"], want[k][1]) for k in want)
    assert abs(sum(r["error"] for r in got.values()) / patches.count() - quantize.commitment_loss(found).first()["loss"]) < 1e-9


def test_files_as_poses(spark, tmp_path):
    import pyarrow as pa

    for k in range(3):
        (tmp_path / f"{k}.bin").write_bytes(bytes([k, 1, 2, 3]))

    def estimate(batches):
        for batch in batches:
            for content in batch.column(1).to_pylist():
                yield pa.RecordBatch.from_pydict({"clip_id": pa.array([content[0]], pa.int64()), "t": pa.array([0], pa.int32()), "pose": pa.array([[[float(x)] for x in content[1:]]], pa.list_(pa.list_(pa.float64())))})

    rows = pose.BinaryFilePoses(str(tmp_path / "*.bin"), estimate).load(spark).collect()
    assert sorted((r["clip_id"], r["pose"]) for r in rows) == [(k, [[1.0], [2.0], [3.0]]) for k in range(3)]


def test_patchify_tails(spark):
    lat = spark.createDataFrame([(1, t, [float(t)]) for t in range(5)], "clip_id long, t int, latent array<double>")
    rows = lambda df: sorted((r["patch_idx"], r["vec"]) for r in df.collect())
    assert rows(quantize.patchify(lat, 2)) == [(0, [0, 1]), (1, [2, 3])]
    assert rows(quantize.patchify(lat, 2, "pad_last"))[-1] == (2, [4, 4])
    assert rows(quantize.patchify(lat, 3, stride=1)) == [(0, [0, 1, 2]), (1, [1, 2, 3]), (2, [2, 3, 4])]


def test_interjoint_is_invariant(spark):
    x = spark.createDataFrame([(0, 0, [[0.0, 0.0], [3.0, 4.0]])], "clip_id long, t int, pose array<array<double>>")
    y = spark.createDataFrame([(0, 0, [[0.0, 0.0], [0.0, 6.0]])], x.schema)
    turned = spark.createDataFrame([(0, 0, [[7.0, 1.0], [1.0, 1.0]])], x.schema)
    assert quantize.interjoint_loss(x, y).first()["loss"] == 1.0 == quantize.interjoint_loss(x, turned).first()["loss"]


def test_gradient():
    p = ModelParams(joints=3, coords=2, dim=4, heads=2, patch=2)
    w = encoder.init_weights(p, 3)
    x = np.random.default_rng(1).standard_normal((6, 3, 2))

    def loss(flat):
        nodes = {k: Node(v) for k, v in training.unpack(flat, w).items()}
        return encoder.clip_loss(x, nodes, None, p)[0], nodes

    flat = training.pack(w)
    node, nodes = loss(flat)
    node.backward()
    g = np.concatenate([(nodes[k].grad if nodes[k].grad is not None else np.zeros_like(nodes[k].value)).ravel() for k in sorted(nodes)])
    for i in np.random.default_rng(2).choice(len(flat), 25, replace=False):
        step = np.zeros_like(flat)
        step[i] = 1e-6
        assert abs((loss(flat + step)[0].value - loss(flat - step)[0].value) / 2e-6 - g[i]) < 1e-5
    # the bottleneck passes gradients on as they are
    q = Node(np.ones((2, 2)))
    s = __import__("seqsearch.functions.autodiff", fromlist=["straight_through"]).straight_through(q, np.full((2, 2), 5.0))
    s.backward()
    assert np.array_equal(s.value, np.full((2, 2), 5.0)) and np.array_equal(q.grad, np.ones((2, 2)))


@pytest.mark.parametrize("p", [ModelParams(), ModelParams(combine="concat"), ModelParams(combine="mean", codebook_attention=True), ModelParams(sequential=True)])
def test_model_shapes(p):
    w = {k: Node(v) for k, v in encoder.init_weights(p).items()}
    x = np.random.default_rng(0).standard_normal((5, p.joints, p.coords))
    codes = np.random.default_rng(1).standard_normal((8, p.patch * p.joints * p.dim))
    loss, parts, hit, patches = encoder.clip_loss(x, w, codes, p)
    loss.backward()
    assert len(hit) == 2 and patches.shape == (2, 128) and parts["commit"] > 0


def test_fit_reduces_loss(spark):
    frames = pose.EmbeddingPoses().load(spark, "/root/testdata/sf0.001")
    fitted = training.fit(frames, ModelParams(epochs=5, warmup_epochs=2, learning_rate=5e-3, codebook=CodebookParams(codes=16)))
    h = fitted.history
    assert h[1]["rec"] < h[0]["rec"] and h[-1]["usage"] > 80 and fitted.codes.shape == (16, 128)
    tok = encoder.tokenize(frames, fitted.weights, fitted.codes)
    assert tok.where(F.size("tokens") != 10).count() == 0
    assert encoder.decode(tok, fitted.weights, fitted.codes).count() == frames.count()


def test_pose_preparation(spark):
    frames = spark.createDataFrame([(0, 0, [[1.0, 1.0], [4.0, 5.0], None]), (0, 1, [[2.0, 2.0], [2.0, 4.0], None])], "clip_id long, t int, pose array<array<double>>")
    a = {r["t"]: r["pose"] for r in pose.align_poses(frames).collect()}
    assert a[0][:2] == [[0, 0], [3, 4]] and a[1][:2] == [[0, 0], [0, 2]]
    back = pose.pack_frames(pose.unpack_frames(frames), 3)
    assert sorted(back.collect()) == sorted(frames.collect())
    points = spark.createDataFrame([("x", 0.0, 0.0), ("x", 1.0, 10.0), ("x", 2.5, 40.0)], "k string, t double, v double")
    assert [(round(r["t"], 3), r["v"]) for r in pose.resample(points, "k", "t", "v", 2).select("t", "v").orderBy("t").collect()] == [(0, 0), (0.5, 5), (1, 10), (1.5, 20), (2, 30), (2.5, 40)]
    last = pose.resample(points, "k", "t", "v", 2, "last").select("t", "v").orderBy("t").collect()
    assert [r["v"] for r in last] == [0, 0, 10, 10, 10, 40]


def test_asof_and_interval(spark):
    left = spark.createDataFrame([(1, "a", "2024-01-01 00:00:10"), (2, "a", "2024-01-01 00:00:20"), (3, "b", "2024-01-01 00:00:20")], "id int, k string, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    right = spark.createDataFrame([(7, "a", "2024-01-01 00:00:05"), (8, "a", "2024-01-01 00:00:20")], "v int, k string, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    back = {r["id"]: r["v"] for r in relational.asof_join(left, right, "k", "ts", ["v"]).collect()}
    ahead = {r["id"]: r["v"] for r in relational.asof_join(left, right, "k", "ts", ["v"], "forward", 15).collect()}
    near = {r["id"]: r["v"] for r in relational.asof_join(left, right, "k", "ts", ["v"], tolerance=2).collect()}
    assert back == {1: 7, 2: 8, 3: None} and ahead == {1: 8, 2: 8, 3: None} and near == {1: None, 2: 8, 3: None}


def test_stream_equals_batch(spark, tmp_path):
    from seqsearch.streaming import stream

    events = io.read_table(spark, "/root/testdata/sf0.001", "events").withColumn("ts", F.col("ts").cast("timestamp"))
    src, path = str(tmp_path / "in"), str(tmp_path / "index")
    events.write.parquet(src)
    live = spark.readStream.schema(events.schema).parquet(src)
    q = stream.sessions(live, "6 hours", "0 seconds").writeStream.outputMode("append").foreachBatch(stream.index_batch(path)).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    batch = stream.sessions(events, "6 hours")
    got = index.read_index(spark, path)[1].count()
    open_ones = batch.where(F.col("start") > events.agg(F.max("ts")).first()[0] - F.expr("interval 13 hours")).count()
    assert batch.count() - open_ones <= got <= batch.count()
    replay = stream.without_replays(events.unionByName(events))
    assert replay.count() == events.count()


def test_stream_matches_and_replays(spark, tmp_path):
    """Closed sessions retrieve from a static base; a replayed event counts once; code counts are kept across batches."""
    from seqsearch.streaming import stream

    events = io.read_table(spark, "/root/testdata/sf0.001", "events").withColumn("ts", F.col("ts").cast("timestamp"))
    src, sink = str(tmp_path / "in"), str(tmp_path / "answers")
    events.unionByName(events).write.parquet(src)
    base = stream.sessions(events, "6 hours").drop("start").persist()
    live = lambda: spark.readStream.schema(events.schema).parquet(src)
    start = lambda df, name: df.writeStream.option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True)
    start(stream.sessions(stream.without_replays(live()), "6 hours", None), "m").outputMode("append").foreachBatch(stream.match_batch(base, sink, retrieve.RetrievalPlan(policy="capped", cap=1000, exclude_self=False))).start().awaitTermination()
    got = spark.read.parquet(sink)
    best = got.where("rank = 1").join(base.select(F.col("seq_id").alias("query_id"), F.col("tokens").alias("a")), "query_id").join(base.select(F.col("seq_id").alias("cand_id"), F.col("tokens").alias("b")), "cand_id")
    assert best.count() > 50 and best.where("a <> b").count() == 0  # no event counted twice: every session finds itself
    codes = stream.event_token()
    start(stream.code_drift(live().select(codes.alias("code"))), "d").outputMode("update").format("memory").queryName("drift").start().awaitTermination()
    want = {r["code"]: 2 * r["n"] for r in events.groupBy(codes.alias("code")).agg(F.count("*").alias("n")).collect()}
    assert {r["code"]: r["hits"] for r in spark.table("drift").groupBy("code").agg(F.max("hits").alias("hits")).collect()} == want


def test_late_rows_are_dropped(spark, tmp_path):
    from seqsearch.streaming import stream

    made = lambda rows: spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp"))
    src = str(tmp_path / "in")
    made([(1, "2024-01-02 00:00:00", 1, "click", 0.0, "")]).coalesce(1).write.parquet(src)
    live = spark.readStream.schema(made([]).schema).option("maxFilesPerTrigger", 1).parquet(src)
    q = stream.histograms(live, "1 hour", delay="1 hour").writeStream.outputMode("append").format("memory").queryName("late_rows").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    for k, at in ((2, "2024-01-03 00:00:00"), (3, "2024-01-01 00:00:00"), (4, "2024-01-05 00:00:00"), (5, "2024-01-07 00:00:00")):
        made([(k, at, 1, "click", 0.0, "")]).coalesce(1).write.mode("append").parquet(src)
        q.processAllAvailable()
    q.stop()
    starts = sorted(str(r["start"])[:10] for r in spark.table("late_rows").collect())
    assert "2024-01-01" not in starts and "2024-01-02" in starts


def test_schema_and_sql_surface(spark):
    from seqsearch.sql import alignment_path, all_similarities, register

    seq = sequences(spark, [[1, 2, 3, 4], [2, 3, 4, 5]])
    assert validate(seq.withColumn("more", F.lit(1)), SEQ).columns == ["seq_id", "class_id", "instance_id", "tokens", "times", "len"]
    with pytest.raises(ValueError):
        validate(seq.drop("len"), SEQ)
    register(spark, seq)
    row = spark.sql("SELECT seq_lcss(a.tokens, b.tokens) l, seq_edr(a.tokens, b.tokens) e, seq_erp(a.tokens, b.tokens) r, seq_twed(a.tokens, b.tokens) t, seq_dtw(a.tokens, b.tokens) d FROM sequences a, sequences b WHERE a.seq_id = 0 AND b.seq_id = 1").first()
    assert tuple(row) == (3, 2, 3.0, 4.375, 2.0)
    assert spark.sql("SELECT count(*) FROM postings").first()[0] == 8
    path = alignment_path([1, 2, 3, 4], [2, 3, 4, 5])
    assert sum(op != "match" for *_, op in path) == 2
    pair = seq.alias("a").join(seq.alias("b"), F.col("a.seq_id") < F.col("b.seq_id")).select(F.col("a.tokens").alias("x"), F.col("b.tokens").alias("y"))
    assert abs(all_similarities(pair, "x", "y").first()["sims"]["edr"] - 0.5) < 1e-12
    assert [tuple(r) for r in spark.sql("SELECT * FROM segments(array(1, 2, 3, 4, 5), 2, 2)").collect()] == [(0, [1, 2]), (2, [3, 4]), (3, [4, 5])]


def test_many_queries_in_one_pass(spark, monkeypatch):
    """More queries than sequences may be broadcast still meet the base by their histograms in one pass."""
    from seqsearch.operators import histogram, onepass, shortlist as short
    from seqsearch.plans.retrieve import retrieve_histogram

    rng = np.random.default_rng(5)
    rows = [(k, rng.integers(0, 6, rng.integers(0, 30)).tolist()) for k in range(90)]
    seq = spark.createDataFrame([(i, t, len(t)) for i, t in rows], "seq_id long, tokens array<int>, len int")
    count = [np.bincount(t, minlength=6) for _, t in rows]
    monkeypatch.setattr(onepass, "MOST_QUERIES", 3)

    def fail(*_, **__):
        raise AssertionError("postings were joined")

    monkeypatch.setattr(short, "cosine_pairs", fail)
    got = {(r["query_id"], r["rank"]): (r["cand_id"], round(r["score"], 9)) for r in retrieve_histogram(seq, seq, 4).collect()}
    for q, _ in rows:
        cos = [(-round(float(count[q] @ count[c] / np.sqrt(float(count[q] @ count[q]) * float(count[c] @ count[c]))) if count[q] @ count[c] else 0.0, 9), c) for c, _ in rows if c != q]
        assert [got[q, k + 1] for k in range(4)] == [(c, -v) for v, c in sorted(cos)[:4]]
    pairs = histogram.cosine_pairs(seq.where("seq_id < 20"), seq)
    assert "Join" not in pairs._jdf.queryExecution().toString()
    want = {(q, c, int(count[q] @ count[c])) for q in range(20) for c in range(90) if q != c and count[q] @ count[c]}
    assert {(r["query_id"], r["cand_id"], r["dot"]) for r in pairs.collect()} == want


def test_stream_result_is_not_on_the_driver(spark):
    from seqsearch.workloads.queries import QUERIES

    before = {t.name for t in spark.catalog.listTables()}
    assert QUERIES["stream_hist"](spark, "/root/testdata/sf0.001").count()
    assert {t.name for t in spark.catalog.listTables()} == before  # a memory sink leaves its table, which the driver holds
