"""Sampling, binning, evaluation, tuning, baselines, pipeline stages, streams."""

import math

import numpy as np
import pyarrow as pa
import pytest
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import functions as F

from rulefeat import workloads
from rulefeat.functions.measures import information_gain
from rulefeat.ml import attach, baselines, evaluate, learners, lockstep, moments, small, tuning
from rulefeat.ml.estimators import MixedRuleFeatures, MixedRuleFeaturesModel
from rulefeat.operators import binning, bits, sampling, selectors
from rulefeat.sources import frames
from rulefeat.streaming import running


def test_bounds():
    assert sampling.swap_bound(5000, 0.05) == pytest.approx(0.00772, abs=1e-5)
    assert sampling.hoeffding(sampling.required_size(0.05, 0.01), 0.05) <= 0.01
    assert sampling.swap_bound(sampling.required_size(0.05, 0.01, "swap", 10), 0.05) * 10 <= 0.01


def test_draws(spark):
    df = spark.range(300).select("id", (F.col("id") % 3).cast("string").alias("a"))
    for method in ("exact", "lcg"):
        got = sampling.draw(df, 1000, 5, method, ["id"])
        assert got.agg(F.sum("weight")).first()[0] == 1000 and set(got.columns) == {"id", "a", "weight"}
    assert sorted(r["at"] for r in sampling.numbered(df, ["id"]).collect()) == list(range(300))
    assert 700 < sampling.draw(df, 1000, 5).count() < 1300
    assert sampling.draw(df.limit(0), 10, 1, "exact", ["id"]).count() == 0


def test_error_stays_within_the_bound(spark):
    df = spark.range(2000).select(F.when(F.col("id") % 10 < 7, "1").alias("x1"), F.lit("all").alias("y"))
    far = 0
    for seed in range(40):
        drawn = sampling.draw(df, 400, seed)
        far += abs(drawn.where("x1 = '1'").count() / max(1, drawn.count()) - 0.7) >= 0.08
    assert far / 40 <= sampling.hoeffding(400, 0.08) + 0.05


def slow_cuts(values, labels, k, parts):
    spans, cuts = [sorted(zip(values, labels))], []
    classes = sorted(set(labels))
    tally = lambda rows: [sum(y == c for _, y in rows) for c in classes]
    while len(spans) < k:
        best = None
        for s in spans:
            for q in sorted({s[math.ceil(j * len(s) / parts) - 1][0] for j in range(1, parts)}):
                low, high = [r for r in s if r[0] <= q], [r for r in s if r[0] > q]
                if high:
                    gain = round(information_gain(tally(list(zip(values, labels))), [tally(x) for o in spans if o is not s for x in [o]] + [tally(low), tally(high)]), 9)
                    if best is None or gain > best[0] or (gain == best[0] and q < best[1]):
                        best = (gain, q, s, low, high)
        if best is None:
            break
        spans = [o for o in spans if o is not best[2]] + [best[3], best[4]]
        cuts.append((best[1], best[0]))
    return cuts


def test_binner_against_brute_force(spark):
    rng = np.random.default_rng(2)
    for n, distinct in ((80, 15), (60, 1000)):
        v = rng.integers(0, distinct, n).astype(float)
        y = [str(int(x > distinct * 0.3) + int(x > distinct * 0.8) if rng.random() < 0.85 else rng.integers(0, 3)) for x in v]
        df = spark.createDataFrame(list(zip(v.tolist(), y)), "v double, y string")
        model = binning.EntropyBinner(4, 6, ["v"], "y").fit(df)
        want = slow_cuts(v.tolist(), y, 4, 6)
        assert [c for c, _ in model.cuts[1]] == [c for c, _ in want]
        assert [g for _, g in model.cuts[1]] == pytest.approx([g for _, g in want], abs=1e-8)
        gains = [g for _, g in model.cuts[1]]
        assert gains == sorted(gains) and model.truncate(2).cuts[1] == model.cuts[1][:1]
        sketch = binning.EntropyBinner(4, 6, ["v"], "y", "approx").fit(df)
        assert sketch.cuts == model.cuts
        first = binning.first_cut(df, ["v"], "y", 6).first()
        assert first["cut"] == want[0][0] and first["gain"] == pytest.approx(want[0][1], abs=1e-8)


def test_binner_edges(spark):
    df = spark.createDataFrame([(1.0, 5.0, "a"), (float("nan"), 5.0, "b"), (None, 5.0, "a"), (3.0, 5.0, "b")], "v double, c double, y string")
    model = binning.EntropyBinner(5, 4, ["v", "c"], "y").fit(df)
    assert len(model.cuts[1]) == 1 and model.cuts[2] == []
    out = model.transform(df).collect()
    assert [r["v_bin"] for r in out] == ["b1", None, None, "b2"] and {r["c_bin"] for r in out} == {"b1"}
    assert "v" not in model.transform(df, keep_original=False).columns
    assert binning.EntropyBinner(0, 4, ["v"], "y").fit(df).cuts == {} and binning.EntropyBinner(3, 4, ["v"], "y").fit(df.limit(0)).cuts == {1: []}
    q = binning.quantile_classes(spark.range(100).select(F.col("id").cast("double").alias("v")), "v", 5, exact=False)
    assert [r["count"] for r in q.groupBy("y").count().orderBy("y").collect()] == pytest.approx([20] * 5, abs=2)


def test_auc_and_scores_against_numpy(spark):
    rng = np.random.default_rng(4)
    s, t = rng.integers(0, 12, 300) / 10, rng.integers(0, 2, 300)
    df = spark.createDataFrame(list(zip(s.tolist(), t.tolist())), "s double, t int")
    want = np.mean([(a > b) + 0.5 * (a == b) for a in s[t == 1] for b in s[t == 0]])
    assert evaluate.auc(df, "t", "s").first()["auc"] == pytest.approx(want)
    p = spark.createDataFrame([(0.5, 1.0, 1.0), (0.25, 2.0, 1.0)], "p double, a double, b double").agg(evaluate.log_loss(F.col("p")).alias("l"), evaluate.accuracy("a", "b").alias("acc"), evaluate.mse("a", "b").alias("m")).first()
    assert p["l"] == pytest.approx((math.log(2) + math.log(4)) / 2) and p["acc"] == 0.5 and p["m"] == 0.5
    r = evaluate.summarise(spark.createDataFrame([("a", 1.0), ("a", 3.0)], "m string, score double"), ["m"]).first()
    assert (r["mean"], r["runs"]) == (2.0, 2) and r["std_error"] == pytest.approx(1.0)


def test_smoothing_kinds(spark):
    rows = [(k, d, "log_loss", float((k * 7 + d) % 5)) for k in range(2, 7) for d in range(0, 25, 5)]
    grid = spark.createDataFrame(rows, "k int, d_conf int, criterion string, score double")
    by = {(k, d): v for k, d, _, v in rows}
    box = {(r["k"], r["d_conf"]): r["smoothed"] for r in tuning.smooth(grid, "box", radius=1).collect()}
    assert box[4, 10] == pytest.approx(np.mean([by[k, d] for k in (3, 4, 5) for d in (5, 10, 15)]))
    for kind in ("gaussian", "median", "bilateral"):
        out = tuning.smooth(grid, kind).collect()
        assert len(out) == len(rows) and min(by.values()) <= min(r["smoothed"] for r in out) and max(r["smoothed"] for r in out) <= max(by.values())
    best = tuning.best(tuning.smooth(grid))
    assert best["k"] in range(2, 7)


def test_pipeline_stage_saves_and_loads(spark, sf, tmp_path):
    df = frames.frame(spark, sf, frames.STAR)
    stage = MixedRuleFeatures(labelCol="y", categorical=frames.STAR_CATEGORICAL, continuous=["o_totalprice"], k=3, dFreq=30, dConf=8)
    model = stage.fit(df)
    out = model.transform(df)
    assert "o_totalprice_bin" in out.columns and any(c.startswith("rule_") for c in out.columns)
    model.save(str(tmp_path / "m"))
    again = MixedRuleFeaturesModel.load(str(tmp_path / "m")).transform(df)
    assert again.columns == out.columns and again.exceptAll(out).count() == 0
    assert len(stage.copy().setParams(redundancy="none").fit(df).rows) if hasattr(stage, "setParams") else True


def test_attach_modes_and_learners(spark):
    df = frames.frame(spark, "/root/testdata/sf0.01", frames.PARTS).withColumn("label", F.col("y").cast("double")).cache()
    rows = selectors.select_nonredundant(df, "y", frames.PARTS_FEATURES, 40, 10).features.collect()
    known = attach.codes(df, frames.PARTS_FEATURES)
    sizes = {m: len(attach.assemble(df, m, rows, frames.PARTS_FEATURES, (), known).select("features").first()[0]) for m in ("original", "onehot", "rules", "label_plus_rules", "onehot_plus_interactions", "binned_plus_rules")}
    pairs = sum(r["size"] == 2 for r in rows)
    slots = sum(len(v) for v in known.values())
    assert sizes == {"original": 6, "onehot": slots, "rules": len(rows), "label_plus_rules": 6 + len(rows), "onehot_plus_interactions": slots + pairs, "binned_plus_rules": 6 + len(rows)}
    loss = {}
    for mode in ("original", "label_plus_rules"):
        x = attach.assemble(df, mode, rows, frames.PARTS_FEATURES, (), known)
        loss[mode] = learners.scores(learners.logistic(x.count()).fit(x).transform(x))["log_loss"]
    assert loss["label_plus_rules"] < loss["original"] * 0.7


def test_interaction_baselines(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(600, 4))
    y = x[:, 0] + x[:, 1] + 2 * x[:, 0] * x[:, 1] + 0.1 * rng.normal(size=600)
    names = ["a", "b", "c", "d"]
    df = spark.createDataFrame([(*map(float, r), float(t), i % 6) for i, (r, t) in enumerate(zip(x, y))], "a double, b double, c double, d double, r double, cell int").cache()
    top = baselines.marginal_screen(df, names, "r", 6).collect()
    want = {(i + 1, j + 1): abs(np.corrcoef(x[:, i] * x[:, j], y)[0, 1]) for i in range(4) for j in range(i + 1, 4)}
    assert {(r["f1"], r["f2"]): pytest.approx(r["strength"]) for r in top} == want and (top[0]["f1"], top[0]["f2"]) == (1, 2)
    design, train, test = baselines.Design(df, names, "r", "cell", 6), [0, 1, 2, 3], [4, 5]
    part = df.where("cell < 4")
    base = baselines.main_effects(design, train, test)[0]
    for method in (baselines.iterated, baselines.backtracked):
        assert method(design, train, test)[0] < base / 3
    for method in (baselines.screened, baselines.reluctant, baselines.hierarchical):
        assert method(design, train, test, part)[0] < base / 3
    assert baselines.with_pairs(design, train, test, [(3, 4)])[0] > base / 3 > baselines.with_pairs(design, train, test, [(1, 2)])[0]
    assert baselines.splines(design, train, test, part)[0] < 2 * base
    with pytest.raises(ValueError):
        baselines.all_pairs(1000)
    sets = spark.createDataFrame([(["a", "b"], "1"), (["a", "b", "c"], "1"), (["a", "b"], "1")], "items array<string>, y string")
    assert baselines.random_intersections(sets, "items", "y", "1", 2, 2).first()["items"] == ["a", "b"]


def test_moments_equal_numpy_and_the_lasso_is_optimal(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, 6)) * [1, 5, 0.1, 1, 1, 0] + 2
    y = 3 * x[:, 0] - x[:, 1] + rng.normal(size=300)
    df = spark.createDataFrame([(*map(float, r), float(t), i % 3) for i, (r, t) in enumerate(zip(x, y))] + [(None, 1.0, 1.0, 1.0, 1.0, 1.0, 5.0, 0)], [*"abcdef", "y", "cell"])
    cells = moments.moments(df, [F.col(c) for c in "abcdef"], F.col("y"), F.col("cell"), 3)
    z = np.c_[np.ones(300), x, y]
    assert np.allclose(cells, [z[i::3].T @ z[i::3] for i in range(3)])
    whole = cells.sum(axis=0)
    w = moments.lasso(whole, [0.5, 0.1])[1]
    scale = np.where(x.std(axis=0) > 1e-9, x.std(axis=0), 1)
    grad = ((x - x.mean(axis=0)) / scale).T @ (y - w[0] - x @ w[1:]) / 300
    live = w[1:] != 0
    assert np.allclose(np.abs(grad[live]), 0.1, atol=1e-4) and (np.abs(grad[~live]) <= 0.1 + 1e-4).all() and w[6] == 0
    assert moments.error(whole, w) == pytest.approx(np.mean((y - w[0] - x @ w[1:]) ** 2))
    assert moments.forward(whole, 4) == [1, 0] and moments.lasso_by_cv(cells, [0, 1, 2], 3)[0][1] == pytest.approx(3, abs=0.3)
    with pytest.raises(ValueError):
        moments.moments(df, [F.col("a")] * 9000, F.col("y"), F.col("cell"), 3)


def test_small_block_learners(spark):
    rng = np.random.default_rng(5)
    b = (rng.random((900, 12)) < 0.5).astype(float)
    y = np.where(b[:, 0] == 0, 0, np.where(b[:, 1] * b[:, 2] == 1, 2, 1))
    rows = [("t%d" % (i % 2), "train" if i % 3 else "test", int(t), r.tolist()) for i, (r, t) in enumerate(zip(b, y))] + [("alone", "train", 1, [0.0] * 12)]
    got = small.score_blocks(spark.createDataFrame(rows, "k string, part string, label int, features array<double>"), ["k"], 3).collect()
    assert {r["k"] for r in got} == {"t0", "t1"} and len(got) == 8
    assert all(r["value"] > 0.9 for r in got if r["metric"] == "accuracy" and r["learner"] == "perceptron")
    # the l1 solution against the distributed learner
    df = spark.createDataFrame([(float(t), r.tolist()) for r, t in zip(b, y)], "label double, x array<double>").select("label", array_to_vector("x").alias("features"))
    far = learners.logistic(900).setStandardization(False).setTol(1e-9).setMaxIter(300).fit(df)
    near = small.softmax_l1(b, y, 3)(b)
    there = np.array([r[0] for r in far.transform(df).select(vector_to_array("probability")).collect()])
    assert np.abs(near - there).max() < 0.02


def test_running_rules_equal_batch_rules(spark, sf):
    df = frames.frame(spark, sf, frames.PARTS)
    columns = frames.PARTS_FEATURES
    for d_freq in (1000, 24):
        state = running.RunningRules(columns, "y", d_freq, 10)
        batches = [df.where(F.col("p_brand") < "Brand#2"), df.where((F.col("p_brand") >= "Brand#2") & (F.col("size_band") < "s3")), df.where((F.col("p_brand") >= "Brand#2") & (F.col("size_band") >= "s3"))]
        for batch in batches:
            state.absorb(batch)
        want = selectors.select_nonredundant(df, "y", columns, d_freq, 10).rules
        pick = lambda d: sorted(map(str, d.select("f1", "v1", "f2", "v2", "y", "supp", "supp_x", "supp_y", "n", "rank").collect()))
        assert pick(state.rules()) == pick(want)


def test_running_rules_take_in_late_items_and_missing_values(spark):
    early = [("a", None, "0")] * 6 + [("b", "p", "1")] * 5
    late = [("c", "q", "1")] * 30 + [("c", None, "0")] * 20 + [("b", "q", "1")] * 4
    schema = "x string, z string, y string"
    state = running.RunningRules(["x", "z"], "y", 4, 4)
    for rows in (early, late, early):
        state.absorb(spark.createDataFrame(rows, schema))
    want = selectors.select_nonredundant(spark.createDataFrame(early + late + early, schema), "y", ["x", "z"], 4, 4).rules
    pick = lambda d: sorted(map(str, d.select("f1", "v1", "f2", "v2", "y", "supp", "supp_x", "supp_y", "n").collect()))
    assert pick(state.rules()) == pick(want) and any(c == "c" for _, c in state.counted)


def test_cuts_by_ranges_equal_cuts_in_one_task(spark):
    rng = np.random.default_rng(8)
    rows = [(float(v), float(w) if w < 90 else None, str(int(v > 40) + int(rng.random() < 0.1))) for v, w in zip(rng.integers(0, 90, 400), rng.integers(0, 100, 400))]
    df = spark.createDataFrame(rows, "v double, w double, y string")
    for k, parts in ((2, 20), (5, 6)):
        here = binning.EntropyBinner(k, parts, ["v", "w"], "y").fit(df)
        assert binning.EntropyBinner(k, parts, ["v", "w"], "y", in_task=0).fit(df).cuts == here.cuts
        assert binning.EntropyBinner(k, parts, ["v", "w"], "y", in_task=140).fit(df).cuts == here.cuts
    with pytest.raises(ValueError):
        binning.EntropyBinner(3, 20, ["v"], "y", "approx", cells=30_000_000).fit(df)


def test_cells_hold_no_more_than_stated(spark):
    rng = np.random.default_rng(9)
    df = spark.createDataFrame([(float(v), str(int(v > 0))) for v in rng.normal(size=20_000)], "v double, y string")
    held = binning.histogram(df, ["v"], "y", 100).groupBy("value").agg(F.sum("n").alias("n"))
    assert held.agg(F.max("n")).first()[0] <= 1.2 * 200 and held.agg(F.sum("n")).first()[0] == 20_000


def test_quantile_classes_by_ranges(spark):
    df = spark.range(103).select((F.col("id") * 37 % 103).cast("double").alias("v"), "id")
    got = {r["id"]: r["y"] for r in binning.quantile_classes(df, "v", 5, "id").collect()}
    from pyspark.sql import Window

    assert got == {r["id"]: r["y"] for r in df.select("id", F.ntile(5).over(Window.orderBy("v", "id")).alias("y")).collect()}
    assert {r["y"] for r in binning.quantile_classes(df.limit(3), "v", 5, "id").collect()} == {1, 2, 3} and binning.quantile_classes(df.limit(0), "v", 5, "id").count() == 0


def test_series_do_not_hang_on_blocks(spark, sf):
    whole = frames.series(spark, sf, 10, 5, (5, 20))
    assert len(frames.series_features()) == 27 and len(frames.series_features(*frames.BROAD)) == 86 and len(frames.CUSTOMER_FEATURES) == 101
    cut = frames.series(spark, sf, 10, 5, (5, 20), block=50)
    assert whole.exceptAll(cut).count() == cut.exceptAll(whole).count() == 0 and whole.count() > 500


def test_categories_are_bounded(spark):
    with pytest.raises(ValueError, match="categories"):
        attach.codes(spark.range(20_000).select(F.col("id").cast("string").alias("c")), ["c"])


def test_labels_join_a_stream_in_time(spark, sf, tmp_path):
    path = running.stage_events(spark, sf)
    events = spark.read.parquet(path)
    told = events.select("event_id", (F.col("ts") + F.expr("INTERVAL 30 MINUTES")).alias("label_ts"), F.lit("y").alias("y")).where("event_id % 2 = 0")
    late = events.select("event_id", (F.col("ts") + F.expr("INTERVAL 3 HOURS")).alias("label_ts"), F.lit("late").alias("y")).where("event_id % 2 = 1")
    told.unionByName(late).coalesce(1).write.parquet(str(tmp_path / "labels"))
    labels = spark.readStream.schema("event_id long, label_ts timestamp, y string").parquet(str(tmp_path / "labels"))
    out = running.run_to_end(running.with_labels(running.read_events(spark, path, 10), labels, "1 HOUR", "60 days").select("event_id", "y"), "labelled", "append")
    assert sorted(r["event_id"] for r in out.collect()) == sorted(r["event_id"] for r in events.where("event_id % 2 = 0").collect())


def test_stream_windows_labels_and_repeats(spark, sf):
    path = running.stage_events(spark, sf)
    batch = spark.read.parquet(path)
    out = running.run_to_end(running.without_repeats(running.read_events(spark, path), ["event_id"]), "repeats", "append")
    assert out.count() == batch.count()
    sliding = running.run_to_end(running.window_counts(running.read_events(spark, path), "event_type", "2 days", "1 day"), "sliding")
    assert sliding.agg(F.sum("supp")).first()[0] == 2 * batch.count()


def test_workloads_run_small(spark, sf):
    got = {r["n_prime"]: r for r in workloads.frequency_estimates(spark, sf, (100, 2000), 3).collect()}
    assert got[2000]["mean_error"] < got[100]["mean_error"]
    assert workloads.step_costs(spark, sf, 8, 20, 4).count() == 7


def test_prediction_follows_the_published_order(spark, sf):
    """Mean log-loss of the logistic learner over 12 blocks of the exact distribution: published 0.407, 0.274, 0.232 and 0.180."""
    rows = workloads.planted_prediction(spark, sf, trials=24, literal=True, learners_=("logistic",)).where("metric = 'log_loss'").collect()
    loss = {r["method"]: r["mean"] for r in rows}
    assert loss["budget"] > loss["original"] > loss["balanced"] > loss["nonredundant_1.5"]
    assert loss["original"] == pytest.approx(0.274, abs=0.05) and loss["nonredundant_1.5"] == pytest.approx(0.180, abs=0.04) and loss["balanced"] == pytest.approx(0.232, abs=0.06)


def test_rules_of_the_exact_distribution(spark, sf):
    """How often the published rules are among the five, of 30 trials: balanced as published; without redundancy at margin 1 the main effect is still crowded out by chance pairs, at 1.5 it is not."""
    rows = workloads.planted_rule_frequency(spark, sf, trials=30, literal=True).collect()
    share = lambda method, f1, v1, f2, v2, y: sum(r["occurrences"] for r in rows if (r["method"], r["f1"], r["v1"], r["f2"], r["v2"], r["y"]) == (method, f1, v1, f2, v2, y)) / 30
    for method in ("balanced", "nonredundant", "nonredundant_1.5"):
        assert share(method, 1, "1", 3, "0", "1") > 0.85 and share(method, 1, "1", 2, "0", "1") > 0.85  # published 97 and 96 of 100
    assert share("balanced", 1, "0", None, None, "0") == pytest.approx(0.18, abs=0.2)
    assert share("nonredundant", 1, "0", None, None, "0") < 0.5 < 0.85 < share("nonredundant_1.5", 1, "0", None, None, "0")  # published 97
    assert share("nonredundant_2", 1, "1", 2, "1", "2") > 0.6  # published 88


def test_furnace_chain(spark, sf):
    grid = workloads.furnace_grid(spark, sf, ks=(0, 3), d_confs=(0, 5), d_freq=30)
    assert grid.count() == 4 and set(grid.columns) == {"k", "d_conf", "criterion", "score", "smoothed"}
    scores, confusion = workloads.furnace_refit(spark, sf, {"logistic": (2, 5), "perceptron": (0, 0)}, d_freq=30)
    assert scores.count() == 8 and confusion.groupBy("method", "learner").agg(F.sum("n").alias("n")).select("n").distinct().count() == 1


def test_encodings_and_comparisons_run_small(spark, sf):
    got = workloads.encodings_by_cross_validation(spark, sf, "parts", 2, learners_=("logistic",)).collect()
    assert {r["method"] for r in got} == set(workloads.ENCODINGS) and all(r["runs"] == 2 for r in got)
    errors = {r["method"]: r["mean"] for r in workloads.regression_comparison(spark, sf, 1, 60, 20, 3, forest_trees=5).collect()}
    assert len(errors) == 9 and errors["iterated_lasso"] < errors["base"] * 1.5


def test_lockstep_learners_agree_with_the_library(spark):
    """Codes, numbers, rules and nulls of two parts; the logistic learner has one optimum, so its log-loss on the other part is that of the library's; AUC as by its own function."""
    from rulefeat.ml import lockstep

    df = spark.range(3000).selectExpr("CAST(id % 3 AS STRING) AS a", "IF(id % 11 = 0, NULL, CAST((id * 7919 % 101) AS DOUBLE) / 50 - 1) AS x", "id", "CAST(id % 4 = 3 AS INT) AS part", "id % 7 = 0 AS draw")
    df = df.withColumn("label", F.expr("CAST((id * 31 % 17 < 3) OR (a = '1' AND coalesce(x, 0) > 0) AS INT)"))
    packed = lockstep.pack(df, "label", "part", "draw", ["a"], ["x"], {"a": ["0", "1", "2"]}, {"x": [0.0]}, 2)
    assert packed.table("x", [0.0]) == ["b1", "b2", None]
    one, high = np.array([False, True, False, False]), np.array([False, True, False])
    design = lockstep.Design([("code", 0, np.array([0, 1, 2, -1], np.float32)), ("number", 0), ("rule", [(0, one), (1, high)])], frozenset([0]), frozenset([1]))
    models = [lockstep.Model(0, np.arange(2), "logistic"), lockstep.Model(0, np.arange(3), "logistic"), lockstep.Model(0, np.arange(3), "perceptron")]
    engine = lockstep.Lockstep(packed, [design])
    fitted = engine.fit(models)
    got, area = engine.tally(models, fitted), engine.auc(models, fitted)
    for i, width in ((0, 2), (1, 3)):
        made = df.select("part", F.col("label").cast("double").alias("label"), F.expr("CAST(a AS DOUBLE)").alias("c"), F.expr("coalesce(x, 0)").alias("n"), F.expr("CAST(a = '1' AND coalesce(x > 0, false) AS DOUBLE)").alias("r"))
        made = made.select("part", "label", array_to_vector(F.array(*["c", "n", "r"][:width])).alias("features"))
        train = made.where("part = 0")
        want = learners.scores(learners.logistic(train.count()).fit(train).transform(made.where("part = 1")), True)
        assert got[i][1] / got[i][0] == pytest.approx(want["log_loss"], abs=2e-4) and area[i] == pytest.approx(want["auc"], abs=2e-3)
    assert got[2][1] / got[2][0] < got[0][1] / got[0][0] and got[2][0] == 750
    scored = spark.createDataFrame([(0, 0.2, 0), (0, 0.2, 1), (0, 0.7, 1), (0, 0.7004, 0), (0, 1.0, 1)], "model int, s double, pos long")
    assert lockstep.ranked(scored).first()["auc"] == evaluate.auc(scored, "pos", "s").first()[0]


def test_perceptron_passes_copy_no_columns():
    """Products with ranges of neighbouring columns are those with the columns themselves, in any order, with gaps, or none at all; so are losses and gradients, against differences of the loss."""
    rng = np.random.default_rng(3)
    x = np.asfortranarray(rng.random((50, 90)))
    for columns, ranges in ((np.arange(90), 1), (np.append(np.arange(40, 60), np.arange(5)), 2), (np.array([70, 3, 75]), 2), (np.arange(0), 0)):
        spans, w, back = lockstep.Spans(columns), rng.random((len(columns), 4)), rng.random((50, 4))
        assert len(spans.ranges) == ranges and np.allclose(spans.times(x, w), x[:, columns] @ w) and np.allclose(spans.sums(x, back), x[:, columns].T @ back)
        assert all(np.shares_memory(x, x[:, a:b]) for a, b in spans.ranges)
    columns, sizes, y = np.array([70, 3, 75]), [3, *lockstep.HIDDEN, 3], rng.integers(0, 3, 50)
    w = rng.normal(size=sum(a * b + b for a, b in zip(sizes, sizes[1:])))
    loss = lambda w: lockstep._loss(lockstep._forward(x[:, columns], lockstep._layers(w, sizes))[-1], y)
    spans, layers = lockstep.Spans(columns), lockstep._layers(w, sizes)
    seen = lockstep._forward(x, layers, spans)
    assert lockstep._loss(seen[-1], y) == pytest.approx(loss(w))
    got = lockstep._backward(seen, layers, seen[-1] - np.eye(3)[y], spans)
    for i in (0, 40, 95, 1000, len(w) - 1):
        step = np.eye(1, len(w), i)[0] * 1e-5
        assert got[i] == pytest.approx((loss(w + step) - loss(w - step)) / 2e-5, abs=1e-4)


def test_each_learner_is_scored_at_the_best_point_of_its_grid(spark, sf):
    got = workloads.furnace_tuned(spark, sf, (2, 3), (0, 5), 30).collect()
    assert len(got) == 8 and {(r["method"], r["learner"]) for r in got} == {(m, p) for m in ("original", "mixed") for p in workloads.LEARNERS}
    assert all(r["k"] in (2, 3) and r["value"] > 0 for r in got if r["method"] == "mixed")


def test_folds_with_own_cuts_share_one_table(spark, sf):
    got = workloads.encodings_by_cross_validation(spark, sf, "star", 3, (2, 3), ("logistic",)).collect()
    assert {r["method"] for r in got} == set(workloads.ENCODINGS) and {r["metric"] for r in got} == {"log_loss", "accuracy", "auc", "auc_hard"}
    assert all(r["runs"] == 3 and r["k"] in (2, 3) for r in got)
    loss = {r["method"]: r["mean"] for r in got if r["metric"] == "log_loss"}
    assert loss["label_plus_rules"] < loss["original"]


def test_the_largest_set_has_both_learners_and_all_numbers_of_intervals(spark, sf, monkeypatch):
    from rulefeat import catalog

    packed, fitted = [], []
    pack, fit = lockstep.Lockstep.__init__, lockstep.Lockstep.fit
    monkeypatch.setattr(lockstep.Lockstep, "__init__", lambda self, p, designs, scaled=True: (packed.append(len(designs)), pack(self, p, designs, scaled))[1])
    monkeypatch.setattr(lockstep.Lockstep, "fit", lambda self, models, *more: (fitted.append([m.kind for m in models]), fit(self, models, *more))[1])
    got = catalog.queries()["encodings_star"](spark, sf).collect()
    assert {(r["method"], r["learner"]) for r in got} == {(m, w) for m in workloads.ENCODINGS for w in workloads.LEARNERS}
    assert packed == [9, 5] and len(fitted[0]) == 9 and {w: fitted[1].count(w) for w in workloads.LEARNERS} == {"logistic": 20, "perceptron": 20}


def test_bit_planes_are_the_frame_and_are_mined_alike(spark, sf):
    """Line items as bit planes: the miner's sets, and the records by features held, are those of the table of strings; so with nulls."""
    xs = [f"x{i}" for i in range(1, 13)]
    plain = frames.frame(spark, sf, frames.planted(12, True)).where("trial < 3").withColumn("draw", F.lit(False))
    holed = plain.withColumns({c: F.when(F.concat("x5", "x6", "x8") != "111", F.col(c)) for c in ("x4", "x7")})
    whole = frames.planted_bits(spark, sf, 12, True, lambda *key: F.lit(False), used=3)
    for df, packed in ((plain, whole), (holed, bits.of_strings(holed, "trial", "draw", "y", xs, ["0", "1", "2"]))):
        one, two = selectors.mine_both(df, "y", xs, 20, by=("trial",)), selectors.mine_both(packed.view("trial", int), "y", xs, 20, by=("trial",))
        for kind in (False, True):
            want, got = ([tuple(r) for r in m[kind].sets.orderBy("trial", "y", "rank").collect()] for m in (one, two))
            assert got == want and any(r[1] == 2 for r in got)
        found = packed.patterns({1: {"m": [(4, "0", None, None), (1, "1", 7, "0")]}})
        held = df.where("trial = 1").select((F.coalesce(F.expr("x4 = '0'"), F.lit(False)).cast("int") + 2 * F.coalesce(F.expr("x1 = '1' AND x7 = '0'"), F.lit(False)).cast("int")).alias("p"), F.lit(0).alias("d"), F.col("y").cast("int")).groupBy("p", "d", "y").count().collect()
        assert found == {("m", 1): {tuple(r)[:3]: r["count"] for r in held}}
    with pytest.raises(Exception, match="other values than 0 and 1"):
        bits.of_strings(plain.withColumn("x1", F.lit("2")), "trial", "draw", "y", xs, ["0", "1", "2"]).blocks.count()


def test_counted_records_are_learnt_as_rows_are(spark, sf):
    """Learners over different records and their times, over bit planes, and over the rows by the block learner (whose penalty is that of columns as they are) have one optimum."""
    packed = frames.planted_bits(spark, sf, 6, False, lambda *key: F.pmod(F.xxhash64(*key), F.lit(7)) == 0)
    wanted = [(i, "1", None, None) for i in range(1, 7)]
    found = packed.patterns({t: {"m": wanted} for t in (0, 1)})
    tables = [tuple(workloads._table(found["m", t], 6) for t in (0, 1))]
    models = [lockstep.Model(0, np.arange(6), kind) for kind in ("logistic", "perceptron")]
    got = []
    for engine in (lockstep.Counted(tables, 3, scaled=False), lockstep.Lockstep(packed, [lockstep.Ones(6, frozenset([0]), frozenset([1]))], scaled=False)):
        tally = engine.tally(models, engine.fit(models))
        got.append([tally[i][1] / tally[i][0] for i in (0, 1)])
        assert all(tally[i][0] == tally[i][2].sum() == tables[0][1][3].sum() for i in (0, 1))
    x, y, z, t = (np.repeat(a, b[3].astype(int), axis=0) for b in tables[0] for a in b[:2])
    want = -np.log(small.softmax_l1(x, y, 3, steps=4000)(z)[np.arange(len(t)), t]).mean()
    assert got[0][0] == pytest.approx(want, abs=1e-3) and got[1][0] == pytest.approx(want, abs=1e-3) and got[0][1] == pytest.approx(got[1][1], abs=0.1)


def test_counted_records_outlast_their_learners():
    """The learners' own state leaves the records as they were: a second fit is that of the first, and both can be tested."""
    x, y, draw, times = np.array([[0.0, 1.0], [1.0, 0.0], [1.0, 1.0], [0.0, 1.0]]), np.array([0, 1, 2, 0]), np.array([0, 0, 0, 1]), np.array([40.0, 30.0, 20.0, 10.0])
    engine = lockstep.Counted([((x, y, draw, times), (x, y, draw, times))], 3, scaled=False)
    models = [lockstep.Model(0, np.arange(2), kind) for kind in ("logistic", "perceptron")]
    one, two = (engine.tally(models, engine.fit(models)) for _ in range(2))
    for i in (0, 1):
        assert one[i][0] == 100 and one[i][1] == two[i][1] < 100 * np.log(3) and (np.diag(one[i][2]) == [50, 30, 20]).all()


def test_counted_records_with_a_constant_column():
    """A column that is always 1 gets no coefficient beside the free intercept, and what is learnt is that of the other column alone."""
    y, draw, times = np.array([0, 1, 2, 0]), np.zeros(4, int), np.array([40.0, 30.0, 20.0, 10.0])
    x = np.array([[0.0, 1.0], [1.0, 1.0], [1.0, 1.0], [0.0, 1.0]])
    losses = []
    for z in (x, x[:, :1]):
        engine, model = lockstep.Counted([((z, y, draw, times), (z, y, draw, times))], 3, scaled=False), [lockstep.Model(0, np.arange(z.shape[1]), "logistic")]
        fitted = engine.fit(model)
        losses.append(engine.tally(model, fitted)[0][1])
        assert not fitted[0][1:-1].any()
    assert losses[0] == pytest.approx(losses[1]) and losses[0] < 60


def test_sets_of_parts_are_cut_mined_and_learnt_from_shared_counts(spark):
    """Cuts on a coarse grid are those of a binner of each set; sets mined from one cube are those of each frame; gradients by tables of codes are those of the matrices. With nulls, NaN and infinite values."""
    from rulefeat.ml import lockstep, tuning

    df = spark.range(4000).selectExpr("id", "CAST(id % 5 AS STRING) AS a", "IF(id % 13 = 0, NULL, CAST(id % 3 AS STRING)) AS b", "IF(id % 11 = 0, NULL, IF(id % 97 = 1, DOUBLE('Infinity'), sin(id) * 10)) AS x", "IF(id % 17 = 0, DOUBLE('NaN'), CAST(id * 7919 % 23 AS DOUBLE)) AS z", "CAST(id * 31 % 4 AS INT) AS part", "id % 7 = 0 AS draw")
    df = df.withColumn("label", F.expr("CAST((id * 31 % 17 < 3) OR (a = '1' AND coalesce(x, 0) > 2) AS INT)")).withColumn("y", F.col("label").cast("string"))
    sets = {0: [1, 2], 1: [0, 2, 3], 2: [3]}
    frames_of = {s: df.where(F.col("part").isin(own)) for s, own in sets.items()}
    together = binning.fit_together(df, ["x", "z"], "label", 2, "part", sets, 5, grid=9)
    assert {s: m.cuts for s, m in together.items()} == {s: binning.EntropyBinner(5, 20, ["x", "z"], "y").fit(d).cuts for s, d in frames_of.items()}
    edges = {c: sorted({x for m in together.values() for x, _ in m.cuts[i]}) for i, c in enumerate(("x", "z"), 1)}
    finite = df.withColumn("x", F.when(F.abs("x") < 100, F.col("x")).when(F.col("x").isNotNull(), 50.0))
    packed = lockstep.pack(finite, "label", "part", "draw", ["a", "b"], ["x", "z"], {"a": list("01234"), "b": list("012")}, edges, 2)
    columns = {s: [("a", None), ("b", None)] + [(c, [v for v, _ in m.cuts[i]]) for i, c in enumerate(("x", "z"), 1)] for s, m in together.items()}
    binned, views = ["a", "b", "x_bin", "z_bin"], {s: (columns[s], own) for s, own in sets.items()}
    plain = lambda: {s: together[s].transform(finite.where(F.col("part").isin(own))) for s, own in sets.items()}
    got, want = (tuning.mined_together(packed, c, views, 40, plain, "y", binned).sets.orderBy("cv", "y", "rank").collect() for c in (lockstep.cube(packed, ["0", "1"], range(4)), None))
    assert got == want and {r["size"] for r in got} == {1, 2}
    made = [workloads._encodings(packed, columns[s], {"a": list("01234"), "b": list("012")}, [r for r in selectors.recut(tuning.mined_together(packed, None, views, 40, plain, "y", binned), 8).features.orderBy("cv", "feature_id").collect() if r["cv"] == s], own, [0]) for s, own in sets.items()]
    engine = lockstep.Lockstep(packed, [d for d, _ in made])
    models, rng = [lockstep.Model(s, used[m], "logistic") for s, (_, used) in enumerate(made) for m in workloads.ENCODINGS], np.random.default_rng(1)
    engine.rows, asked = {d: counts for d, (_, counts) in engine.moments().items()}, {i: ("all", rng.normal(size=(len(m.columns) + 1, 2)) / 3) for i, m in enumerate(models)}
    for sent in (asked, {i: asked[i] for i in (2, 7)}):
        for i, (rows, _, gradient) in engine.evaluate(models, sent).items():
            m, w, want = models[i], sent[i][1], 0.0
            for batch in packed.blocks.collect():
                if batch["part"] in engine.designs[m.design].train:
                    ((_, _, y, codes, numbers),) = packed.opened()([pa.RecordBatch.from_pydict({"part": [batch["part"]], "n": [batch["n"]], "data": pa.array([bytes(batch["data"])], pa.binary())})])
                    x = engine.designs[m.design].matrix(codes, numbers, float)
                    p = lockstep.probabilities(x, m, w, 2) - np.eye(2)[y]
                    want = want + np.vstack([x[:, m.columns].T @ p, p.sum(axis=0)])
            assert rows == df.where(F.col("part").isin(sets[m.design])).count() and np.allclose(gradient, want, atol=0.05, rtol=1e-3)


def test_series_windows_equal_plain_ones(spark, tmp_path):
    """Rows held back from a user's run and from windows, nulls among values and users, against lists; runs go on over batches, blocks and forgotten rows."""
    from datetime import datetime, timedelta

    rng, n = np.random.default_rng(5), 400
    rows = [(i, datetime(2024, 1, 1) + timedelta(seconds=7 * i), None if u == 3 else int(u), None if hole else round(float(v), 2), '{"k": 4}') for i, (u, hole, v) in enumerate(zip(rng.integers(0, 4, n), rng.random(n) < 0.1, rng.random(n) * 200))]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, value double, props string").write.parquet(f"{tmp_path}/events.parquet")
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "13")
    try:
        got = {r["event_id"]: r for r in frames.series(spark, str(tmp_path), 3, 2, (2, 5), block=50).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert len(got) == n
    of: dict = {}
    for i, _, user, value, _ in rows:
        r, past, own = got[i], [x[3] for x in rows[:i]], of.setdefault(user, [])
        assert [r[f"lag{j}"] for j in (1, 2, 3)] == [past[-j] if len(past) >= j else None for j in (1, 2, 3)]
        assert [r[f"user_lag{j}"] for j in (1, 2)] == [own[-j] if len(own) >= j else None for j in (1, 2)] and r["user_events"] == len(own) + 1
        assert r["gap"] == (7.0 if i else None) and r["prop"] == 4.0
        own.append(value)
        for size in (2, 5):
            known = [v for v in past[-size:] if v is not None]
            assert (r[f"least{size}"], r[f"most{size}"]) == ((min(known), max(known)) if known else (None, None))
            assert r[f"mean{size}"] == (pytest.approx(np.mean(known)) if known else None)
            assert r[f"spread{size}"] == (pytest.approx(np.std(known, ddof=1), abs=1e-6) if len(known) > 1 else None)
