"""The forms of the queries that larger tables need: against plain forms on small ones."""

import threading
from dataclasses import replace

import duckdb
import numpy as np
import pandas as pd
import pytest

from seqsearch.config import WEIGHTS, CodebookParams, MetricParams, ModelParams
from seqsearch.functions import wavefront
from seqsearch.functions.autodiff import Node
from seqsearch.operators import encoder, nearest, onepass, shortlist, training
from seqsearch.operators.shortlist import ranked
from seqsearch.plans import retrieve
from seqsearch.sources import pose
from seqsearch.workloads import queries as workload
from seqsearch.workloads.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
SCHEMA = "seq_id bigint, class_id string, instance_id int, tokens array<int>, times array<double>, len int"


def made(spark, rows):
    return spark.createDataFrame([(i, str(i % 7), 0, t, None, len(t)) for i, t in rows], SCHEMA)


def plain(asked, base, k, exclude_self):
    out = []
    for q, a in asked:
        every = []
        for c, b in base:
            if c == q and exclude_self:
                continue
            x, y = np.bincount(a, minlength=9), np.bincount(b, minlength=9)
            every.append((-round(float(x @ y / np.sqrt(max(1, (x @ x) * (y @ y)))), 9), c))
        out += [(q, r + 1, c, -v) for r, (v, c) in enumerate(sorted(every)[:k])]
    return sorted(out)


@pytest.mark.parametrize("k, exclude_self", [(1, True), (3, True), (3, False), (40, True), (250, True), (900, False)])
def test_nearest_equals_all_pairs(spark, monkeypatch, k, exclude_self):
    """Copies, multiples (cosine 1), empty sequences and words of one side only; groups small, so that most are left out."""
    monkeypatch.setattr(nearest, "GROUP", 8)
    rng = np.random.default_rng(5)
    base = [(int(i), rng.integers(0, 6, rng.integers(0, 12)).tolist()) for i in rng.permutation(300)]
    base += [(1000 + i, t * (1 + i % 2)) for i, t in base[:60]]
    asked = base[::5] + [(5000, [7, 8]), (5001, [1, 8, 8])]
    got = nearest.nearest(made(spark, asked), made(spark, base), k, exclude_self).collect()
    assert sorted((r.query_id, r.rank, r.cand_id, round(r.cosine, 9)) for r in got) == plain(asked, base, k, exclude_self)


@pytest.mark.parametrize("name", ["retrieve_periodic", "eval_studio"])
def test_equal_histograms_are_compared_once(spark, monkeypatch, name):
    """More sequences than different histograms: each is compared once, and the histograms of a side are read once, whatever their number."""
    monkeypatch.setattr(shortlist, "ONE_PASS", 0)
    monkeypatch.setattr(onepass, "MOST_KEPT", 10)  # sequences, not histograms, are many
    seen, kinds = [], nearest.kinds
    monkeypatch.setattr(nearest, "kinds", lambda df: seen.append((df.count(), kinds(df))) or seen[-1][1])
    got = QUERIES[name](spark, SF).toPandas()
    assert name not in ORACLES or rows(got) == wanted(name)
    assert seen and all(len(k.ids) == n for n, k in seen) and (name == "eval_studio" or any(len(k.begin) - 1 < n for n, k in seen))
    spark.catalog.clearCache()


def test_answers_have_an_honest_size(spark):
    """Spark's estimate of the size of the answers grows with them, so that no join broadcasts them to the driver."""
    base = made(spark, [(i, [i % 5, i % 3]) for i in range(3000)])
    plan = nearest.nearest(base, base, 40)._jdf.queryExecution().optimizedPlan()
    assert int(str(plan.stats().sizeInBytes())) >= 3000 * 40 * 8


def test_nearest_leaves_groups_out():
    rng = np.random.default_rng(5)
    counts = rng.integers(0, 30, (20_000, 5)).astype(float)
    base = nearest.Grouped(np.arange(20_000), counts, *nearest.groups(counts))
    seen = []
    cosine = base.cosine
    base.cosine = lambda c, n, rows: seen.append(len(rows)) or cosine(c, n, rows)
    order, begin = nearest.groups(counts)
    rows = order[begin[7] : begin[8]]
    best = base.best(rows, counts[rows], 3, True)
    assert sum(seen) < 10_000 and len(best.query) == 3 * len(rows)


def rows(df):
    df = df[sorted(df.columns)].astype(object)
    return sorted((tuple("~" if pd.isna(v) else round(float(v), 6) if isinstance(v, float) else v for v in r) for r in df.itertuples(index=False)), key=str)


def wanted(name):
    c = duckdb.connect()
    for t in ("events", "documents"):
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return rows(c.execute(ORACLES[name]).df())


#: Evaluations of many queries by histogram, and shortlists that grow with the base.
DEALT_OUT = ["eval_loo", "eval_confusion", "eval_leave_k", "eval_per_class_rollup", "eval_rank_distribution", "eval_cross_tempo", "shortlist_printed"]


@pytest.mark.parametrize("name", DEALT_OUT)
def test_answers_need_no_shuffle(spark, monkeypatch, name):
    """Each task has the whole answer of its queries: no candidates are sent to be ranked."""
    monkeypatch.setattr(shortlist, "ONE_PASS", 0)
    got = QUERIES[name](spark, SF)
    assert "windowspecdefinition(query_id" not in got._jdf.queryExecution().executedPlan().toString()
    assert rows(got.toPandas()) == wanted(name)


def test_many_queries_meet_the_base_in_blocks(spark, monkeypatch):
    """More queries than one matrix holds: no postings are joined and no pairs summed up, and the pairs are all that share a word."""
    monkeypatch.setattr(onepass, "_CELLS", 90)
    monkeypatch.setattr(onepass, "MOST_QUERIES", 10)
    rng = np.random.default_rng(2)
    base = made(spark, [(int(i), rng.integers(0, 30, j % 12).tolist()) for j, i in enumerate(rng.permutation(200))])
    asked = base.where("seq_id % 2 = 0")
    got = retrieve.cosine_pairs(asked, base)
    assert "Aggregate" not in got._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(onepass, "every_cosine", lambda *a: None)
    keys = lambda df: sorted((r.query_id, r.cand_id, r.dot, round(r.cosine, 9)) for r in df.collect())
    assert keys(got) == keys(retrieve.cosine_pairs(asked, base)) and len(keys(got)) > 1000


@pytest.mark.parametrize("by", ["max", "mean"])
def test_classes_are_summed_up_in_place(spark, monkeypatch, by):
    """Classes longer than a slice, a null class, an empty sequence: as from the pairs, but no pair is sent."""
    monkeypatch.setattr(onepass, "_CELLS", 300)
    rng = np.random.default_rng(3)
    base = made(spark, [(i, rng.integers(0, 5, 1 + i % 9).tolist()) for i in range(200)] + [(900, [])])
    base = base.selectExpr("seq_id", "nullif(class_id, '6') as class_id", "instance_id", "tokens", "times", "len")
    asked = base.where("seq_id % 20 = 0")
    got = retrieve.retrieve_classes_histogram(asked, base, by=by)
    assert "Aggregate" not in got._jdf.queryExecution().executedPlan().toString()
    want = retrieve.retrieve_classes(retrieve.cosine_pairs(asked, base).withColumnRenamed("cosine", "score"), base, by=by)
    keys = lambda df: sorted((r.query_id, r.rank, r.class_id or "", round(r.score, 9)) for r in df.collect())
    assert keys(got) == keys(want) and len(keys(got)) == 30


#: All rows of a quadratic result.
EVERY_PAIR = ["dtw_band", "ngram_cosine", "combined_score"]


@pytest.mark.parametrize("name", EVERY_PAIR)
def test_pairs_are_not_sent(spark, name):
    """Pairs come out of one pass over the base: no join of ids, no shuffle of what it makes, no rounding a pair of copies."""
    plan = QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan and plan.index("MapInArrow") > plan.index("BroadcastHashJoin") > plan.index("Generate")
    assert plan[: plan.index("MapInArrow")].count("Exchange") <= plan[: plan.index("MapInArrow")].count("BroadcastExchange")


def test_copies_are_compared_once(spark, monkeypatch):
    """Copies of queries, of others, more than a row holds, empty sequences: every pair has its row and value."""
    monkeypatch.setattr(onepass.copies, "__defaults__", (False, 3, False))
    rng = np.random.default_rng(4)
    kinds = [[], [1], [1, 2, 2], *(rng.integers(0, 5, 9).tolist() for _ in range(6))]
    base = made(spark, [(i, kinds[i % 9 if i % 2 else i % 3]) for i in range(120)])
    asked = base.where("seq_id % 20 = 0")
    plan = retrieve.RetrievalPlan()
    names = ["query_id", "cand_id", *(f"s_{m}" for m in plan.metrics), "score"]
    keys = lambda df: sorted(tuple(round(v, 9) for v in r) for r in df.select(*names).collect())
    got = keys(retrieve.score_all(asked, base, plan))
    assert len(got) == 6 * 119 and got == keys(retrieve.score_pairs(retrieve.all_pairs(asked, base), asked, base, plan))


@pytest.mark.parametrize("how", ["retrieve_exhaustive", "retrieve_bounded"])
@pytest.mark.parametrize("exclude_self", [True, False])
def test_copies_are_scored_once(spark, monkeypatch, how, exclude_self):
    """More copies than answers, of queries and others, in any order of ids: the answers are those of all pairs."""
    rng = np.random.default_rng(4)
    kinds = [[], [1], [1, 2, 2], *(rng.integers(0, 5, 9).tolist() for _ in range(6))]
    base = made(spark, [(int(i), kinds[j % 9 if j % 2 else j % 3]) for j, i in enumerate(rng.permutation(120))])
    asked = base.where("seq_id % 20 < 3")
    plan = retrieve.RetrievalPlan(exclude_self=exclude_self)
    scanned = []
    scan = onepass.scan
    monkeypatch.setattr(retrieve, "scan", lambda block, rows, *a: scanned.append((len(block.ids), rows.count())) or scan(block, rows, *a))
    keys = lambda df: sorted((r.query_id, r.rank, r.cand_id, round(r.score, 9)) for r in df.collect())
    got = keys(getattr(retrieve, how)(asked, base, plan))
    assert max(scanned[0]) <= 9 and len(got) == 3 * 18
    assert got == keys(ranked(retrieve.score_pairs(retrieve.all_pairs(asked, base, exclude_self), asked, base, plan), "score", 3))


#: Queries whose exhaustive answers come from sequences that are scored once.
ONCE = ["retrieve_bounded", "set_compare", "shortlist_recall", "eval_cross_tempo_aligned"]


@pytest.mark.parametrize("name", ONCE)
def test_exhaustive_answers_from_copies(spark, monkeypatch, name):
    made_once = []
    copies = onepass.copies
    monkeypatch.setattr(retrieve, "copies", lambda *a, **k: made_once.append(1) or copies(*a, **k))
    assert rows(QUERIES[name](spark, SF).toPandas()) == wanted(name) and len(made_once) >= 2


@pytest.mark.parametrize("exclude_self", [True, False])
def test_segments_of_copies(spark, monkeypatch, exclude_self):
    """Segments of equal sequences are scored once; the answers are those of the joins of all pairs."""
    rng = np.random.default_rng(6)
    kinds = [rng.integers(0, 4, int(n)).tolist() for n in (0, 3, 8, 9, 20, 20, 31)]
    base = made(spark, [(int(i), kinds[j % 7 if j % 2 else j % 3 + 3]) for j, i in enumerate(rng.permutation(70))])
    asked = base.where("seq_id % 20 < 3")
    plan = retrieve.RetrievalPlan(weights={"lcss": 1.0}, exclude_self=exclude_self)
    keys = lambda df: sorted(tuple(r) for r in df.collect())
    got = retrieve.retrieve_segments(asked, base, 8, 3, plan)
    assert "NestedLoop" not in got._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(retrieve, "every_pair", lambda *a: None)
    assert keys(got) == keys(retrieve.retrieve_segments(asked, base, 8, 3, plan))


def test_variants_are_fitted_at_once(spark, monkeypatch):
    """All variants are under way before any ends, and their histories are those of fits one by one."""
    p = ModelParams(epochs=2, warmup_epochs=1, codebook=CodebookParams(codes=4))
    frames = pose.EmbeddingPoses().load(spark, SF).where("clip_id < 4")
    grid = {"base": p, "low": replace(p, lam=0.1), "sequential": replace(p, sequential=True)}
    want = [training.fit(frames, v).history[-1] for v in grid.values()]
    together, fit_clips = threading.Barrier(3, timeout=60), training.fit_clips
    monkeypatch.setattr(training, "fit_clips", lambda *a: together.wait() is not None and fit_clips(*a))
    got = training.ablate(frames, p, grid)
    assert [g["variant"] for g in got] == list(grid)
    for g, w in zip(got, want, strict=True):
        assert all(abs(g[k] - w[k]) < 1e-9 for k in w)


@pytest.mark.parametrize("weights", [{"lcss": 1.0}, {"lcss": 0.5, "edr": 0.5}])
@pytest.mark.parametrize("window, hop", [(8, 3), (16, 8), (40, 7)])
def test_segments_are_scored_in_place(spark, monkeypatch, weights, window, hop):
    """No row for a pair of a query and a segment: tasks cut the sequences and keep the best; the answers are those of all pairs."""
    monkeypatch.setattr(onepass, "_WINDOWS", 40)
    rng = np.random.default_rng(6)
    kinds = [rng.integers(0, 4 + j % 3, int(n)).tolist() for j, n in enumerate((0, 1, 3, 8, 9, 20, 20, 31, 90, *rng.integers(0, 60, 60)))]
    base = made(spark, [(int(i), kinds[j % len(kinds)]) for j, i in enumerate(rng.permutation(150))])
    asked = base.where("seq_id % 20 < 3")
    plan = retrieve.RetrievalPlan(weights=weights)
    keys = lambda df: sorted(tuple(r) for r in df.collect())
    got = retrieve.retrieve_segments(asked, base, window, hop, plan)
    shown = got._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in shown and "max(" not in shown  # the best segment of a sequence is not looked for among sent ones
    monkeypatch.setattr(retrieve, "best_segments", lambda *a: None)
    assert keys(got) == keys(retrieve.retrieve_segments(asked, base, window, hop, plan)) and len(keys(got)) > 60


def test_revival_shows_in_the_last_line(spark):
    """More codes than patches, so some are dead after the only epoch with codes: their revival is in what is reported."""
    p = ModelParams(epochs=2, warmup_epochs=1, codebook=CodebookParams(codes=64))
    frames = pose.EmbeddingPoses().load(spark, SF).where("clip_id < 4")
    grid = {"base": p, "no_revival": replace(p, codebook=replace(p.codebook, revive=False))}
    base, dead = training.ablate(frames, p, grid)
    assert base["rec"] != dead["rec"]
    fitted = training.fit(frames, p)
    w, seen = {k: Node(v) for k, v in fitted.weights.items()}, []
    for r in encoder.clips(frames).orderBy("clip_id").collect():
        _, parts, hit, _ = encoder.clip_loss(encoder.tensor(r.frames, r.n, p), w, fitted.codes, p)
        seen.append((parts["rec"], hit))
    assert abs(base["rec"] - np.mean([rec for rec, _ in seen])) < 1e-9 and len(seen) == 4
    assert base["usage"] == 100 * len(np.unique(np.concatenate([hit for _, hit in seen]))) / 64


def test_a_step_is_one_task_over_its_clips(spark):
    """A step reads the partition that has its clips, not the whole table, and its sums are those of a plain loop over them."""
    p = ModelParams(epochs=3, warmup_epochs=1, batch=3, codebook=CodebookParams(codes=4))
    frames = pose.EmbeddingPoses().load(spark, SF)
    steps = encoder.clips(frames).count() // p.batch
    spark.sparkContext.setJobGroup("one_task", "")
    training.fit(frames, p)
    tracker = spark.sparkContext.statusTracker()
    stages = [tracker.getStageInfo(s) for j in tracker.getJobIdsForGroup("one_task") for s in tracker.getJobInfo(j).stageIds]
    spark.sparkContext.setJobGroup("others", "")
    assert steps > 5 and sum(s is not None and s.numTasks > 1 and s.numCompletedTasks > 0 for s in stages) < 12 * p.epochs
    assert sum(s is not None and s.numTasks == 1 for s in stages) >= p.epochs * (steps - 1)

    rows, weights = encoder.clips(frames).persist(), encoder.init_weights(p)
    codes = np.random.default_rng(3).standard_normal((4, p.patch * p.joints * p.dim))
    dealt, places, _ = training._by_step(rows, 5, steps)
    mine = rows.selectExpr("*", f"pmod(xxhash64(5, clip_id), {steps}) as step").orderBy("clip_id").collect()
    assert set(places) == {r.step for r in mine} and all(len(at) == 1 for at in places.values())
    for step, at in places.items():
        got = training._sums(dealt, step, at, weights, codes, p, 1.0, 1.0, 4, codes.shape[1])
        w, rec, gradient, hits, seen = {k: Node(v) for k, v in weights.items()}, 0.0, 0.0, np.zeros(4), 0
        for r in (r for r in mine if r.step == step):
            loss, parts, hit, _ = encoder.clip_loss(encoder.tensor(r.frames, r.n, p), w, codes, p)
            loss.backward()
            rec, hits, seen = rec + parts["rec"], hits + np.bincount(hit, minlength=4), seen + 1
            gradient = gradient + np.concatenate([w[k].grad.ravel() for k in sorted(w)])
            for node in w.values():
                node.grad = None
        size = len(gradient)
        assert np.allclose(got[:size], gradient) and np.allclose(got[size], rec) and got[size + 4] == seen
        assert np.array_equal(got[size + 5 : size + 9], hits)


@pytest.mark.parametrize("prune", [True, False])
def test_different_sequences_are_scored_without_a_sweep(monkeypatch, prune):
    """Bounded and exhaustive scoring of sequences that are no copies: the best are those of all similarities by the sweep."""
    rng = np.random.default_rng(8)
    seqs = [rng.integers(0, 5, n) for n in rng.integers(0, 100, 90)]
    names, want = list(WEIGHTS), []
    for q in range(9):
        s = wavefront.similarities(names, [seqs[q]] * 90, seqs)
        score = sum(WEIGHTS[k] * s[k] for k in names)
        order = [c for c in np.lexsort((np.arange(90), -np.round(score, 9))) if c != q][:3]
        want += [(q, c, round(score[c], 9)) for c in order]
    monkeypatch.setattr(wavefront, "sweep", None)
    scorer = onepass.Scorer(onepass.QueryBlock(np.arange(9), seqs[:9], None), 3, WEIGHTS, MetricParams(), True, prune)
    for at in range(0, 90, 30):
        scorer.feed(np.arange(at, at + 30), seqs[at : at + 30], None)
    assert sorted(zip(scorer.best.query, scorer.best.cand, np.round(scorer.best.value, 9), strict=True)) == sorted(want)


@pytest.mark.parametrize("band", [None, 0, 1, 5, 40])
def test_dtw_by_bytes(band):
    """All lengths, also empty ones; values up to the largest: as the sweep."""
    rng = np.random.default_rng(3)
    seqs = [rng.integers(0, 4, n) for n in (0, 0, 1, *rng.integers(0, 40, 300))] + [np.full(n, k) for n, k in ((200, 1), (200, 2), (130, 3))]
    a, b = ([seqs[k] for k in rng.permutation(len(seqs))] for _ in range(2))
    a, b = [*a, seqs[-3], seqs[-1]], [*b, seqs[-2], seqs[-2]]
    p = MetricParams(dtw_band=band)
    assert np.array_equal(wavefront.quick("dtw", a, b, p), wavefront.dtw(a, b, p))
    assert wavefront.quick("dtw", [np.zeros(300)], [np.ones(3)], p) is None


#: Queries all of whose pairs go by the forms without sweeps.
NO_SWEEP = ["combined_score", "dtw_band", "set_compare", "shortlist_recall"]


@pytest.mark.parametrize("name", NO_SWEEP)
def test_query_takes_no_sweep(spark, monkeypatch, name):
    monkeypatch.setattr(wavefront, "sweep", None)  # modules travel by value, so executors have none either
    assert rows(QUERIES[name](spark, SF).toPandas()) == wanted(name)


#: Queries that read the sequences in several jobs.
READ_ONCE = ["combined_score", "set_compare", "shortlist_recall"]


@pytest.mark.parametrize("name", READ_ONCE)
def test_events_are_read_once(spark, monkeypatch, name):
    """The events are scanned and shuffled once, without times, for all jobs of a query."""
    seen, table = spark.sparkContext.accumulator(0), workload.table

    def counted(spark, d, name):
        df = table(spark, d, name)

        def run(batches):
            for batch in batches:
                seen.add(batch.num_rows)
                yield batch

        return df.mapInArrow(run, df.schema)

    monkeypatch.setattr(workload, "table", counted)
    got = QUERIES[name](spark, SF)
    assert rows(got.toPandas()) == wanted(name) and seen.value == table(spark, SF, "events").count()
    spark.catalog.clearCache()


#: Queries that need the exhaustive answers only, not every score.
BOUNDED = ["set_compare", "shortlist_recall"]


@pytest.mark.parametrize("name", BOUNDED)
@pytest.mark.parametrize("many", [500, 0])
def test_answers_by_the_bounded_form(spark, monkeypatch, name, many):
    """Pairs that can't be answers are not aligned, with and without a first look; the first look takes no sweep either."""
    monkeypatch.setattr(retrieve, "MANY", many)
    monkeypatch.setattr(wavefront, "sweep", None)
    pruned, scan = [], onepass.scan
    monkeypatch.setattr(retrieve, "scan", lambda *a: pruned.append((a[7], a[9] is not None)) or scan(*a))
    assert rows(QUERIES[name](spark, SF).toPandas()) == wanted(name) and pruned == [(True, many == 0)]
    spark.catalog.clearCache()


#: Prices for which the bounds of terms differ.
PRICES = [MetricParams(), MetricParams(twed="original"), MetricParams(lam=0.5), MetricParams(lam=2.0, nu=0.0), MetricParams(nu=1.0, gap=2.0), MetricParams(beta=0.125), MetricParams(beta=1.0, gap=0.5), MetricParams(edr_eps=1.0, twed_cost="abs")]


@pytest.mark.parametrize("params", PRICES)
@pytest.mark.parametrize("timed", [False, True])
def test_bounds_leave_the_best(params, timed):
    """Values that other terms bound: no bound is below the value, so the best are those of all pairs, for any prices."""
    rng = np.random.default_rng(11)
    seqs = [rng.integers(0, 4, n) for n in (0, 1, *rng.integers(1, 30, 148))]
    times = [np.cumsum(rng.random(len(t))) for t in seqs] if timed else None
    found = []
    for prune in (True, False):
        scorer = onepass.Scorer(onepass.QueryBlock(np.arange(12), seqs[:12], times and times[:12]), 3, WEIGHTS, params, True, prune)
        for at in range(0, 150, 50):
            scorer.feed(np.arange(at, at + 50), seqs[at : at + 50], times and times[at : at + 50])
        found.append(sorted(zip(scorer.best.query, scorer.best.cand, np.round(scorer.best.value, 9), strict=True)))
    assert found[0] == found[1] and len(found[0]) == 36


def test_few_pairs_get_the_costly_terms():
    """Over sequences of five tokens that are no copies: TWED, the costliest, is left for a few pairs."""
    rng = np.random.default_rng(12)
    seqs = [rng.integers(0, 5, n) for n in rng.integers(45, 100, 1500)]
    scorer = onepass.Scorer(onepass.QueryBlock(np.arange(10), seqs[:10], None), 3, WEIGHTS, MetricParams(), True, True)
    pairs, align = {}, scorer._align
    scorer._align = lambda term, q, *a: pairs.update({term: pairs.get(term, 0) + len(q)}) or align(term, q, *a)
    for at in range(0, 1500, 300):
        scorer.feed(np.arange(at, at + 300), seqs[at : at + 300], None)
    assert scorer.pairs == 14_990 and pairs["twed"] < scorer.pairs / 4 and pairs["erp"] < scorer.pairs * 0.55
