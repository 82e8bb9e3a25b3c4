"""Counting, measures, selectors, features: worked examples, brute force, properties."""

import itertools
import math
import warnings

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from rulefeat.functions import measures, sql_functions
from rulefeat.operators import counts, features, items, itemsets, params, rules, selectors
from rulefeat.plans import complexity, pair_plans
from rulefeat.sources import frames, generators, tables

MICRO = [r.split() for r in "a p k 1/a p k 1/a q k 1/a q k 0/b p k 0/b p k 0/b p k 1/b q k 0/b q k 0/b q k 0/a p k 1/b p k 0".split("/")]
COLUMNS = ["x1", "x2", "x3"]


@pytest.fixture(scope="module")
def micro(spark):
    return spark.createDataFrame([tuple(r) for r in MICRO], "x1 string, x2 string, x3 string, y string")


def brute(data, columns, label="y"):
    """All counts of one and two items by class, from collected rows."""
    out = {}
    for r in data:
        held = [(i, r[c]) for i, c in enumerate(columns, 1) if r[c] is not None]
        for size in (1, 2):
            for combo in itertools.combinations(held, size):
                key = (combo, r[label])
                out[key] = out.get(key, 0) + 1
    return out


def shape(r):
    return ((r["f1"], r["v1"]),) if r["f2"] is None else ((r["f1"], r["v1"]), (r["f2"], r["v2"]))


def test_micro_table(micro):
    chosen = selectors.select_nonredundant(micro, "y", COLUMNS, 12, 3)
    got = [(shape(r), r["y"]) for r in chosen.rules.orderBy("rank").collect()]
    assert got == [(((1, "a"), (2, "p")), "1"), (((1, "a"),), "1"), (((1, "b"),), "0")]
    assert chosen.features.count() == 3
    printed = selectors.select_nonredundant(micro, "y", COLUMNS, 12, 3, redundancy="printed").rules.orderBy("rank").collect()
    assert [shape(r) for r in printed] == [((1, "a"), (2, "p")), ((1, "a"),), ((1, "a"), (3, "k"))]
    scored = {(shape(r), r["y"]): r for r in measures.with_measures(chosen.mined.sets).collect()}
    assert len(scored) == 12
    r = scored[((1, "b"),), "0"]
    assert (r["supp"], r["supp_x"]) == (6, 7) and r["conf"] == pytest.approx(6 / 7) and r["lift"] == pytest.approx(1.4694, abs=1e-4) and r["rconf"] == pytest.approx(4.2857, abs=1e-4)
    assert scored[((3, "k"),), "1"]["rconf"] == pytest.approx(1.0, abs=1e-5)
    small = selectors.select_nonredundant(micro, "y", COLUMNS, 8, 8).rules.collect()
    assert all(r["size"] == 1 for r in small) and len(small) == 6
    lost = rules.dropped_as_redundant(measures.with_measures(chosen.mined.sets)).collect()
    assert {(shape(r), r["y"]) for r in lost} == {(((1, "b"), (3, "k")), "0"), (((2, "q"), (3, "k")), "0"), (((1, "a"), (3, "k")), "1"), (((2, "p"), (3, "k")), "1")}


def test_golden_parts(spark):
    df = frames.frame(spark, "/root/testdata/sf0.01", frames.PARTS)
    got = selectors.select_nonredundant(df, "y", frames.PARTS_FEATURES, 40, 10).rules.orderBy("rank").collect()
    assert [(shape(r), r["y"], r["supp"], r["supp_x"]) for r in got[:4]] == [(((2, "LARGE"), (3, "s5")), "3", 70, 70), (((2, "STANDARD"), (3, "s5")), "2", 75, 76), (((2, "MEDIUM"), (3, "s5")), "2", 68, 70), (((3, "s1"),), "0", 391, 394)]
    assert [round(r["rconf"], 3) for r in got[1:4]] == [856.676, 388.36, 96.728]


def test_fast_filter_equals_the_loop(spark):
    df = frames.frame(spark, "/root/testdata/sf0.01", frames.PARTS)
    scored = measures.with_measures(selectors.mine(df, "y", frames.PARTS_FEATURES, 60, True).sets).cache()
    rows = [r.asDict() for r in scored.collect()]
    for redundancy, margin in (("strict", 1.0), ("printed", 1.0), ("strict", 2.0)):
        fast = {(shape(r), r["y"]) for r in rules.nonredundant(scored, redundancy=redundancy, margin=margin).collect()}
        assert fast == {(shape(r), r["y"]) for r in rules.nonredundant_loop(rows, "rconf", redundancy, margin)}


rows = st.lists(st.tuples(*[st.sampled_from(["a", "b", "c", None])] * 3, st.sampled_from(["0", "1", "2"])), min_size=1, max_size=40)


@settings(max_examples=6, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(rows, st.integers(1, 20))
def test_top_sets_are_the_top_of_all_sets(spark, data, d_freq):
    dicts = [dict(zip([*COLUMNS, "y"], r)) for r in data]
    df = spark.createDataFrame(data, "x1 string, x2 string, x3 string, y string")
    every = brute(dicts, COLUMNS)
    classes = sorted({r["y"] for r in dicts})
    for per_class in (False, True):
        got = {(shape(r), r["y"]): r for r in selectors.mine(df, "y", COLUMNS, d_freq, per_class).sets.collect()}
        order = lambda k: (-every[k], len(k[0]), *k[0][0], *(k[0][1] if len(k[0]) == 2 else (-1, "")), k[1])
        if per_class:
            want = {k for c in classes for k in sorted((k for k in every if k[1] == c), key=order)[: max(1, d_freq // len(classes))]}
        else:
            want = set(sorted(every, key=order)[:d_freq])
        assert set(got) == want
        for k, r in got.items():
            assert r["supp"] == every[k] and r["n"] == len(data) and r["supp_x"] == sum(every.get((k[0], c), 0) for c in classes)
        for combo, y in got:
            if len(combo) == 2 and per_class:
                assert all(((one,), y) in got for one in combo)


@pytest.mark.parametrize("plan", ["explode", "gram", "bits", "auto"])
def test_pair_plans_agree(spark, plan):
    df = frames.frame(spark, "/root/testdata/sf0.001", frames.PARTS)
    columns = frames.PARTS_FEATURES
    wanted = [(2, "LARGE"), (2, "SMALL"), (3, "s5"), (3, "s1"), (6, "r0"), (6, "r1")]
    got = {(shape(r), r["y"]): r["supp"] for r in counts.pairs(df, columns, "y", wanted, plan=plan).collect()}
    every = brute([r.asDict() for r in df.collect()], columns)
    assert got == {k: n for k, n in every.items() if len(k[0]) == 2 and all(x in wanted for x in k[0])}
    brute_df = itemsets.bruteforce_pairs(df, ["p_partkey"], columns, "y").where("f1 = 2 AND v1 = 'LARGE' AND f2 = 3 AND v2 = 's5'").collect()
    assert {(shape(r), r["y"]): r["supp"] for r in brute_df}.items() <= got.items()


def test_plan_choice_at_its_borders(spark):
    assert pair_plans.choose_plan(20, 10) == "bits" and pair_plans.choose_plan(21, 10) == "gram" and pair_plans.choose_plan(21, pair_plans.DENSE) == "explode"
    assert pair_plans.choose_plan(pair_plans.GRAM_ITEMS, 100) == "gram" and pair_plans.choose_plan(pair_plans.GRAM_ITEMS + 1, 100) == "explode"


@pytest.mark.parametrize("literal,held", [(20_000, 1 << 23), (5, 1 << 23), (6, 40)])
def test_plans_agree_in_groups_with_weights_and_missing_groups(spark, monkeypatch, literal, held):
    monkeypatch.setattr(pair_plans, "LITERAL_ITEMS", literal)
    monkeypatch.setattr(pair_plans, "HELD", held)
    data = [(None if i % 5 == 0 else i % 3, "ab"[i % 2], "pqr"[i % 3], "uv"[i * i % 7 % 2], str(i % 2), 1 + i % 4) for i in range(60)]
    df = spark.createDataFrame(data, "g int, x1 string, x2 string, x3 string, y string, w long")
    kept = spark.createDataFrame([(g, f, v) for g in (None, 0, 1) for f, v in ((1, "a"), (2, "p"), (2, "q"), (3, "u"), (1, "b"))] + [(2, 1, "a"), (2, 3, "v")], "g int, f1 int, v1 string")
    want = {}
    for g, *xs, y, w in data:
        held_ = [(i, x) for i, x in enumerate(xs, 1) if (i, x) in ({(1, "a"), (3, "v")} if g == 2 else {(1, "a"), (2, "p"), (2, "q"), (3, "u"), (1, "b")})]
        for i, a in enumerate(held_):
            for b in held_[i + 1 :]:
                want[g, a, b, y] = want.get((g, a, b, y), 0) + w
    for plan in ("auto", "explode", "gram", "join"):
        got, n = counts.pairs_of(df, COLUMNS, "y", kept, ("g",), "w", plan=plan)
        assert {(r["g"], (r["f1"], r["v1"]), (r["f2"], r["v2"]), r["y"]): r["supp"] for r in got.collect()} == want and n == 6


def test_groups_without_a_name_are_mined_too(spark):
    df = spark.createDataFrame([(None, "a", "p", "0")] * 4 + [(None, "b", "p", "1")] * 3 + [(1, "a", "q", "1")] * 5 + [(1, "b", "q", "0")], "g int, x1 string, x2 string, y string")
    both = selectors.mine_both(df, "y", ["x1", "x2"], 8, by=("g",))
    for per_class in (False, True):
        alone = selectors.mine(df.where("g IS NULL"), "y", ["x1", "x2"], 8, per_class).sets
        key = lambda d: sorted((shape(r), r["y"], r["supp"], r["supp_x"], r["supp_y"], r["n"]) for r in d.collect())
        assert key(both[per_class].sets.where("g IS NULL")) == key(alone)
        assert selectors.recut(both[per_class], 3).rules.where("g IS NULL").count() == min(3, alone.count())


def test_many_frequent_items_stay_a_table(spark, monkeypatch):
    df = frames.frame(spark, "/root/testdata/sf0.001", frames.PARTS)
    want = selectors.select_by_threshold(df, "y", frames.PARTS_FEATURES, 0.02, 0.3).rules.collect()
    monkeypatch.setattr(pair_plans, "LITERAL_ITEMS", 3)
    got = selectors.select_by_threshold(df, "y", frames.PARTS_FEATURES, 0.02, 0.3).rules.collect()
    assert sorted(map(str, got)) == sorted(map(str, want)) and any(r["size"] == 2 for r in got)


def test_floors(micro):
    every = selectors.select_nonredundant(micro, "y", COLUMNS, 100, 100).rules.collect()
    floored = selectors.select_nonredundant(micro, "y", COLUMNS, 100, 100, min_count=3, min_score=1.0).rules.collect()
    assert floored and all(r["supp"] >= 3 and r["rconf"] >= 1.0 for r in floored) and len(floored) < len(every)


def test_vote_takes_the_first_rule_that_fits(spark):
    chosen = spark.createDataFrame([(1, 1, "a", None, None, "0", 5, 0.6), (2, 1, "a", 2, "p", "1", 3, 0.9)], "size int, f1 int, v1 string, f2 int, v2 string, y string, supp long, conf double")
    records = spark.createDataFrame([(1, "a", "p"), (2, "a", None), (3, None, "p")], "k int, x1 string, x2 string")
    assert [tuple(r) for r in rules.vote(records, chosen, ["x1", "x2"], "z", "k").orderBy("key").collect()] == [(1, "1", 0.9), (2, "0", 0.6), (3, "z", None)]
    assert {r["prediction"] for r in rules.vote(records, chosen.limit(0), ["x1", "x2"], "z", "k").collect()} == {"z"}


def test_scratch_needs_a_shared_folder_off_one_machine():
    from rulefeat import storage

    class Conf:
        def get(self, *a):
            return None

    class Session:
        conf, sparkContext = Conf(), type("C", (), {"master": "spark://host:7077"})()

    with pytest.raises(RuntimeError, match="checkpoint"):
        storage.scratch_root(Session())


def test_budget_equals_threshold_between_supports(spark):
    df = frames.frame(spark, "/root/testdata/sf0.01", frames.PARTS)
    mined = selectors.mine(df, "y", frames.PARTS_FEATURES, 40, False).sets.collect()
    supports = sorted((r["supp"] for r in mined), reverse=True)
    cut = next(i for i in range(20, 39) if supports[i] > supports[i + 1]) + 1
    a = selectors.mine(df, "y", frames.PARTS_FEATURES, cut, False).sets.collect()
    b = selectors.select_by_threshold(df, "y", frames.PARTS_FEATURES, min_count=supports[cut - 1], min_conf=0.0).mined.sets.collect()
    assert {(shape(r), r["y"]) for r in a} == {(shape(r), r["y"]) for r in b}


def test_threshold_extremes(micro):
    none = selectors.select_by_threshold(micro, "y", COLUMNS, 0.99, 0.99)
    assert none.rules.count() == 0 and none.features.columns == ["feature_id", "size", "f1", "v1", "f2", "v2"]
    with pytest.warns(UserWarning, match="thresholds"):
        selectors.select_by_threshold(micro, "y", COLUMNS, 0.01, 0.0, max_rules=3)


def test_edges(spark, micro):
    empty = micro.limit(0)
    for f in (selectors.select_by_budget, selectors.select_balanced, selectors.select_nonredundant):
        assert f(empty, "y", COLUMNS, 10, 5).features.count() == 0
    one = spark.createDataFrame([("a'b", 'q"=,', "0")], "`odd name` string, b string, y string")
    got = selectors.select_nonredundant(one, "y", ["odd name", "b"], 10, 5)
    assert got.rules.where("rconf = 0").count() == got.rules.count() > 0
    names = {r["name"] for r in features.named(got.features, ["odd name", "b"]).collect()}
    assert "odd name=a'b" in names
    assert features.apply(one, got.features.collect(), ["odd name", "b"]).first()["rule_1"] == 1
    nulls = spark.createDataFrame([(None, "u", "0"), (None, None, "1"), ("a", "u", None)], "a string, b string, y string")
    assert counts.singles(nulls, ["a", "b"], "y").count() == 1
    assert counts.singles(nulls, ["a", "b"], "y", null_policy="category").count() == 4
    with pytest.raises(ValueError):
        items.Roles("y", ("y",))


def test_lists_weights_and_roles(spark):
    df = spark.createDataFrame([(["p", "q", "p"], "u", "1", 3), (["q"], "v", "0", 2)], "tags array<string>, b string, y string, w long")
    got = {(r["f"], r["v"], r["y"]): r["supp"] for r in counts.singles(df, ["tags", "b"], "y", weight="w").collect()}
    assert got == {(1, "p", "1"): 3, (1, "q", "1"): 3, (2, "u", "1"): 3, (1, "q", "0"): 2, (2, "v", "0"): 2}
    pair = counts.pairs(df, ["tags", "b"], "y", [(1, "q"), (2, "u"), (2, "v")], weight="w", plan="explode").collect()
    assert {(shape(r), r["y"]): r["supp"] for r in pair} == {(((1, "q"), (2, "u")), "1"): 3, (((1, "q"), (2, "v")), "0"): 2}
    roles = items.infer_roles(spark.createDataFrame([(1, 1.5, "a", "x")], "i int, d double, s string, y string"), "y")
    assert roles.categorical == ("i", "s") and roles.continuous == ("d",)


def test_partitions_and_label_names_change_nothing(micro):
    base = [(shape(r), r["y"]) for r in selectors.select_nonredundant(micro, "y", COLUMNS, 12, 5).rules.orderBy("rank").collect()]
    moved = selectors.select_nonredundant(micro.repartition(5).orderBy(F.desc("x2")), "y", COLUMNS, 12, 5).rules.orderBy("rank").collect()
    assert base == [(shape(r), r["y"]) for r in moved]
    renamed = micro.withColumn("y", F.concat(F.lit("c"), "y"))
    assert [(s, "c" + y) for s, y in base] == [(shape(r), r["y"]) for r in selectors.select_nonredundant(renamed, "y", COLUMNS, 12, 5).rules.orderBy("rank").collect()]


def test_feature_application(spark, micro):
    rules_ = spark.createDataFrame([(1, 1, "a", None, None, "0"), (1, 1, "a", None, None, "1"), (2, 1, "a", 2, "p", "1")], "size int, f1 int, v1 string, f2 int, v2 string, y string")
    found = features.from_rules(rules_)
    assert found.count() == 2
    assert [r["name"] for r in features.named(found, COLUMNS).orderBy("feature_id").collect()] == ["x1=a", "x1=a, x2=p"]
    rows_ = found.orderBy("feature_id").collect()
    wide = features.apply(micro, rows_, COLUMNS).collect()
    assert [(r["rule_1"], r["rule_2"]) for r in wide] == [(int(r["x1"] == "a"), int(r["x1"] == "a" and r["x2"] == "p")) for r in wide]
    assert features.apply(micro, rows_, COLUMNS, "indexes").first()["rule_indexes"] == [0, 1]
    assert features.product_pairs(found).collect() == [(1, 2)]


def test_levelwise_equals_pattern_growth(spark):
    tx = spark.createDataFrame([(sorted({f"i{(a * b) % 7}" for b in range(1, 1 + a % 6)}),) for a in range(1, 90)], "items array<string>")
    mine = {tuple(r["items"]): r["supp"] for r in itemsets.levelwise(tx, min_support=0.08).collect()}
    growth = {tuple(r["items"]): r["supp"] for r in itemsets.pattern_growth(tx, 0.08).collect()}
    assert mine == growth and max(map(len, mine)) >= 3
    tagged = itemsets.levelwise(spark.createDataFrame([(["a", "b", "class=1"],), (["a", "class=1"],), (["a", "class=0"],)], "items array<string>"), min_count=1)
    found = {(tuple(r["x"]), r["y"]): (r["supp"], r["supp_x"]) for r in rules.class_rules(tagged, ["class=0", "class=1"]).collect()}
    assert found[("a",), "class=1"] == (2, 3) and found[("a", "b"), "class=1"] == (1, 1)
    general = rules.general_rules(tagged.select("items", "supp"), 3, 0.5).collect()
    assert all(not set(r["x"]) & set(r["y"]) for r in general) and any(len(r["x"]) == 2 for r in general)


def test_measures_and_sql_functions(spark):
    sql_functions.register(spark)
    row = spark.sql("SELECT rule_conf(6, 7) c, rule_lift(6, 7, 7, 12) l, rule_rconf(6, 7, 7, 12) r").first()
    assert row["c"] == pytest.approx(6 / 7) and row["l"] == pytest.approx(1.4694, abs=1e-4) and row["r"] == pytest.approx(4.2857, abs=1e-4)
    assert [tuple(r) for r in spark.sql("SELECT p.* FROM (SELECT array(3, 1, 2) AS ids) t, LATERAL pairs_of(ids) p ORDER BY 1, 2").collect()] == [(1, 2), (1, 3), (2, 3)]
    entropy = spark.sql("SELECT label_entropy(y) AS e FROM VALUES ('a'), ('a'), ('b'), ('b') AS t(y)").first()["e"]
    assert entropy == pytest.approx(math.log(2)) == measures.entropy([2, 2])
    assert measures.information_gain([2, 2], [[2, 0], [0, 2]]) == pytest.approx(math.log(2))


def test_parameters():
    assert [(b.d_freq, b.d_conf) for b in (params.suggest(14, 2), params.suggest(23, 2), params.suggest(6, 4))] == [(30, 15), (40, 20), (40, 10)]
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        params.validate(params.Budgets(10, 8), 3)
    assert seen
    assert params.suggest_lean(100).d_freq == 10


def test_step_costs_stay_below_prediction(spark, sf):
    df = frames.frame(spark, sf, frames.planted(12))
    seen = {r["step"]: r for r in complexity.observe(df, "y", [f"x{i}" for i in range(1, 13)], 30, 5).collect()}
    for step, touched, held in complexity.predict(df.count(), 12, 3, 30, 5):
        if step in seen:
            assert seen[step]["held"] <= max(held, 30) and seen[step]["touched"] <= max(touched, 30) + 1


def test_planted_structure_is_found(spark):
    df = generators.planted_rules(spark, 1000, 20, 6, seed=3)
    xs = [f"x{i}" for i in range(1, 21)]
    mined = selectors.mine(df, "y", xs, 45, True, by=("trial",))
    found = selectors.recut(mined, 5, margin=1.5).rules.groupBy("f1", "v1", "f2", "v2", "y").count().collect()
    often = {(shape(r), r["y"]) for r in found if r["count"] >= 4}
    assert {(((1, "0"),), "0"), (((1, "1"), (2, "0")), "1"), (((1, "1"), (3, "0")), "1")} <= often
    only_major = selectors.recut(selectors.mine(df, "y", xs, 45, False, by=("trial",)), 5, "conf", None).rules.select("y").distinct().collect()
    assert [r["y"] for r in only_major] == ["0"]


def test_generator_source_and_formats(spark, tmp_path):
    generators.register_sources(spark)
    df = spark.read.format("planted_rules").option("rows", 500).option("p", 5).load()
    assert df.count() == 500 and df.columns == ["x1", "x2", "x3", "x4", "x5", "y"]
    assert 0.8 < generators.frequent_sets(spark, 2000).agg(F.avg(F.col("x1").cast("int"))).first()[0] < 1
    for f in ("parquet", "orc", "json", "csv"):
        df.write.format(f).option("header", "true").save(str(tmp_path / f))
        assert tables.read_table(spark, str(tmp_path / f), f, schema=df.schema).count() == 500
    tables.save(df, str(tmp_path / "by"), ("y",))
    assert spark.read.parquet(str(tmp_path / "by")).where("y = 0").count() > 0
    tables.register_views(spark, "/root/testdata/sf0.001", ["nation"])
    assert spark.sql("SELECT count(*) FROM nation").first()[0] == 25


def test_package_is_shipped_once_from_many_threads(spark, monkeypatch):
    import time

    from rulefeat import storage, workloads

    calls = []
    monkeypatch.setattr(storage, "_SHIPPED", set())
    monkeypatch.setattr(type(spark.sparkContext), "addPyFile", lambda self, path: (calls.append(path), time.sleep(0.2)))
    workloads.in_parallel([lambda: storage.ship_package(spark)] * 4)
    assert len(calls) == 1


def test_wide_records_are_counted_without_a_row_an_item(spark, monkeypatch):
    from rulefeat.operators import counts
    from rulefeat.operators.items import long_items

    names = [f"a{i}" for i in range(1, 11)]
    rows = [(i % 3 if i % 7 else None, "xyz"[i % 3] if i % 11 else None, *[None if (i * j) % 5 == 0 else float("nan") if j == 10 and i % 4 == 0 else float(i * j % 4) for j in range(1, 11)]) for i in range(200)]
    df = spark.createDataFrame(rows, "g int, y string, " + ", ".join(f"{n} double" for n in names))
    monkeypatch.setattr(counts, "BLOCK", 17)
    for by, policy, label in ((("g",), "skip", True), ((), "category", False)):
        got = counts.singles(df, names, "y", by, null_policy=policy, with_label=label)
        assert "Generate" not in got._jdf.queryExecution().executedPlan().toString()
        want = long_items(df, names, "y", by, None, policy, label).groupBy(*by, "f", "v", "y").count()
        assert sorted(map(str, got.collect())) == sorted(str(r).replace("count=", "supp=") for r in want.collect()) != []
        assert counts.singles(df.limit(0), names, "y", by, null_policy=policy).count() == 0
