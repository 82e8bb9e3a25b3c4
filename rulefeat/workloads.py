"""The experiments on the given tables: each returns a DataFrame of measured rows."""

from __future__ import annotations

import random
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .ml import attach, baselines, evaluate, learners, lockstep, tuning
from .operators import binning, bits, features as feature_ops, params, sampling, selectors
from .operators.items import value_of
from .plans import complexity
from .sources import frames, generators
from .storage import materialise

METHODS = {
    "budget": lambda mined: selectors.recut(mined[False], 5, "conf", None),
    "balanced": lambda mined: selectors.recut(mined[True], 5, "rconf", None),
    "nonredundant": lambda mined: selectors.recut(mined[True], 5),
    "nonredundant_1.5": lambda mined: selectors.recut(mined[True], 5, margin=1.5),
    "nonredundant_2": lambda mined: selectors.recut(mined[True], 5, margin=2.0),
}


def _xs(p: int) -> list[str]:
    return [f"x{i}" for i in range(1, p + 1)]


def frequency_estimates(spark: SparkSession, sf_dir: str, sizes=(100, 500, 1000, 2000, 5000), draws: int = 20, literal_rows: int | None = None) -> DataFrame:
    """(n_prime, mean_error, max_error, recovered, bound): error of the five most frequent sets and share of draws that recover the true top four."""
    df = generators.frequent_sets(spark, literal_rows) if literal_rows else frames.frame(spark, sf_dir, frames.frequency_bits())
    xs = _xs(10)
    ones = materialise(df.select(*[F.when(F.col(c) == "1", F.col(c)).alias(c) for c in xs], "y"), "bits")
    n = ones.count()
    full = selectors.mine(ones, "y", xs, 5, False).sets.select("f1", "v1", "f2", "v2", "rank", (F.col("supp") / n).alias("p"))
    truth = {(r["f1"], r["f2"]): (r["p"], r["rank"]) for r in full.collect()}
    top4 = {k for k, (_, rank) in truth.items() if rank <= 4}
    out = []
    for m in sizes:
        errors, hits = [], 0
        for seed in range(draws):
            drawn = ones.sample(True, m / n, seed)
            size = max(1, drawn.count())
            got = {(r["f1"], r["f2"]): r["supp"] / size for r in selectors.mine(drawn, "y", xs, 5, False).sets.collect()}
            errors += [abs(got[k] - truth[k][0]) for k in got if k in truth]
            hits += top4 <= set(got)
        out.append((m, sum(errors) / max(1, len(errors)), max(errors, default=0.0), hits / draws, sampling.hoeffding(m, 0.05)))
    return spark.createDataFrame(out, "n_prime int, mean_error double, max_error double, recovered double, bound double")


def run_times(spark: SparkSession, sf_dir: str, sizes=(100, 500, 1000, 2000, 5000), widths=(10, 25, 50, 100), repeats: int = 2) -> DataFrame:
    """(axis, value, seconds, items): time of one selector run against the sample size at ten features, and against the number of features at 5000 draws."""
    out = []

    def run(df: DataFrame, p: int) -> float:
        best = float("inf")
        for _ in range(repeats):
            start = time.perf_counter()
            selectors.select_nonredundant(df, "y", _xs(p), 45, 5).features.count()
            best = min(best, time.perf_counter() - start)
        return best

    for p in sorted({10, *widths}):
        drawn = materialise(sampling.draw(frames.frame(spark, sf_dir, frames.planted(p)), 5000, 1, "poisson").drop("weight"), "draw")
        if p in widths:
            out.append(("p", p, run(drawn, p), p * 5000))
        if p == 10:
            n = drawn.count()
            for m in sizes:
                part = materialise(drawn.sample(False, min(1.0, m / n), 3), "part")
                out.append(("n_prime", m, run(part, p), p * m))
    return spark.createDataFrame(out, "axis string, value int, seconds double, items long")


def planted_rule_frequency(spark: SparkSession, sf_dir: str, p: int = 99, constant: bool = False, trials: int | None = None, literal: bool = False) -> DataFrame:
    """(method, f1, v1, f2, v2, y, occurrences, trials): how often each rule is among the five of a trial, by method; all trials are mined in one job.

    literal: the generator's exact distribution with 1000 rows a trial, else blocks of line items.
    """
    df = generators.planted_rules(spark, 1000, p, trials or 100, constant) if literal else frames.frame(spark, sf_dir, frames.planted(p, constant, used=trials))
    df = materialise(df, "trials")
    mined = selectors.mine_both(df, "y", _xs(p), 45, by=("trial",))
    n, out = df.select("trial").distinct().count(), None
    for name, cut in METHODS.items():
        one = evaluate.rule_frequency(cut(mined).rules).select(F.lit(name).alias("method"), "f1", "v1", "f2", "v2", "y", "occurrences", F.lit(n).alias("trials"))
        out = one if out is None else out.unionByName(one)
    return out


def planted_prediction(spark: SparkSession, sf_dir: str, p: int = 99, constant: bool = False, trials: int | None = None, literal: bool = False, learners_=("logistic", "perceptron")) -> DataFrame:
    """(method, learner, metric, mean, deviation, std_error, runs): prediction from the generated features alone, and from the original ones; trained on one block, tested on the next.

    The records are bit planes (Bits). All blocks are mined by one run for both kinds of budget. A method's few features make few different records, so its learners need no more than how often
    each occurs in a block, counted in one pass; those of the original features go ahead in lockstep over the planes.
    """
    xs = _xs(p)
    if literal:
        df = materialise(generators.planted_rules(spark, 1000, p, trials or 100, constant).withColumn("draw", held_out("trial", *xs)), "trials")
        packed = bits.of_strings(df, "trial", "draw", "y", xs, ["0", "1", "2"])
    else:
        packed = frames.planted_bits(spark, sf_dir, p, constant, held_out, trials)
    mined = selectors.mine_both(packed.view("block", lambda t: None if t % 2 else t // 2), "y", xs, 45, by=("block",))
    chosen = None
    for name, cut in METHODS.items():
        one = cut(mined).features.select(F.lit(name).alias("method"), "block", "feature_id", "f1", "v1", "f2", "v2")
        chosen = one if chosen is None else chosen.unionByName(one)
    wanted: dict[int, dict[str, list[tuple]]] = {}
    for r in chosen.orderBy("block", "method", "feature_id").collect():  # a budget's number for each block
        wanted.setdefault(r["block"], {}).setdefault(r["method"], []).append((r["f1"], r["v1"], r["f2"], r["v2"]))
    of_both = packed.view("block", lambda t: t // 2)
    found, named, tables = of_both.patterns(wanted), [], []
    for block, of in wanted.items():
        for method, antecedents in of.items():
            named.append((method, block))
            tables.append(tuple(_table(found.get((method, t), {}), len(antecedents)) for t in (2 * block, 2 * block + 1)))
    rows = _scored(lockstep.Counted(tables, packed.classes, scaled=False), named, [t[0][0].shape[1] for t in tables], learners_)
    designs = [lockstep.Ones(p, frozenset([2 * b]), frozenset([2 * b + 1])) for b in wanted]
    rows += _scored(lockstep.Lockstep(packed, designs, scaled=False), [("original", b) for b in wanted], [p] * len(designs), learners_)
    scored = spark.createDataFrame(rows, "method string, block int, learner string, metric string, value double")
    return evaluate.summarise(scored, ["method", "learner", "metric"], "value")


def _table(patterns: dict[tuple[int, int, int], int], width: int) -> tuple[np.ndarray, ...]:
    """(records, labels, draws, times) of Bits.patterns() of one block."""
    keys = np.array(sorted(patterns), np.int64).reshape(-1, 3)
    return (keys[:, :1] >> np.arange(width) & 1).astype(float), keys[:, 2], keys[:, 1], np.array([patterns[tuple(k)] for k in keys.tolist()], float)


def _scored(engine: lockstep.Lockstep, named: list[tuple[str, int]], widths: list[int], learners_) -> list[tuple]:
    """(method, block, learner, metric, value) of each design's learners over all its columns."""
    points = [(i, learner) for i in range(len(named)) for learner in learners_]
    models = [lockstep.Model(i, np.arange(widths[i]), learner) for i, learner in points]
    got = engine.tally(models, engine.fit(models))
    return [(*named[points[at][0]], points[at][1], m, float(v)) for at, tally in got.items() for m, v in tuning.measures(tally).items()]


def in_parallel(tasks: list[Callable], threads: int = 4) -> list:
    """Results of independent drivers of small jobs, in order."""
    with ThreadPoolExecutor(threads) as pool:
        return [f.result() for f in [pool.submit(t) for t in tasks]]


LEARNERS = ("logistic", "perceptron")
CLASS_CODES = {"low": 0.0, "proper": 1.0, "high": 2.0}
CLASS_NAMES = sorted(CLASS_CODES, key=CLASS_CODES.__getitem__)


def furnace_frame(spark: SparkSession, sf_dir: str, wide: bool = False) -> tuple[DataFrame, list[str]]:
    """The time-ordered events with a numeric label, their part (0 train, 1 validation, 2 test) and a draw of rows that a perceptron holds out, and their features: 27, or 86 if wide."""
    shape = frames.BROAD if wide else frames.NARROW
    label = F.element_at(F.create_map(*[F.lit(x) for kv in CLASS_CODES.items() for x in kv]), F.col("y"))
    part = F.when(F.col("split") == "train", 0).when(F.col("split") == "validation", 1).otherwise(2)
    df = frames.series(spark, sf_dir, *shape).withColumns({"label": label, "part": part, "draw": held_out("event_id")}).drop("split", "user_id", "ts", "value")
    return materialise(df, "series"), frames.series_features(*shape)


def held_out(*key: str) -> Column:
    """True for about 15 of 100 rows, whatever their order."""
    return F.pmod(F.xxhash64(*key, F.lit(7)), F.lit(100)) < 15


def furnace_grid(spark: SparkSession, sf_dir: str, wide: bool = False, ks=(0, *range(2, 11)), d_confs=(0, 5, 10, 15, 20, 25, 30, 35, 40), d_freq: int = 150, criterion: str = "log_loss", learner: str = "logistic") -> DataFrame:
    """(k, d_conf, criterion, score, smoothed) on the validation part: every number of intervals with every number of rules."""
    df, columns = furnace_frame(spark, sf_dir, wide)
    return materialise(tuning.smooth(tuning.grid_together(df, ks, d_confs, d_freq, "y", columns, CLASS_NAMES, (learner,), criterion)[learner]), "grid")


def furnace_refit(spark: SparkSession, sf_dir: str, best: dict[str, tuple[int, int]], wide: bool = False, d_freq: int = 150, frame: tuple[DataFrame, list[str]] | None = None) -> tuple[DataFrame, DataFrame]:
    """Scores (method, learner, k, d_conf, metric, value) and confusion (method, learner, k, d_conf, truth, prediction, n) on the test part, of the chosen (k, d_conf) of each learner and of the original features."""
    df, columns = frame or furnace_frame(spark, sf_dir, wide)
    chosen = [(method, learner, *point) for learner in LEARNERS for method, point in (("original", (0, 0)), ("mixed", best[learner]))]
    rows, counted = [], []
    for one, (got, counts) in zip(chosen, tuning.refit_together(df, [c[1:] for c in chosen], d_freq, "y", columns, CLASS_NAMES)):
        rows += [(*one, m, v) for m, v in got.items()]
        counted += [(*one, str(float(t)), str(float(p)), int(n)) for (t, p), n in np.ndenumerate(counts) if n]
    keys = "method string, learner string, k int, d_conf int, "
    return spark.createDataFrame(rows, keys + "metric string, value double"), spark.createDataFrame(counted, keys + "truth string, prediction string, n long")


def furnace_tuned(spark: SparkSession, sf_dir: str, ks=(2, 4, 8), d_confs=(0, 10, 25, 40), d_freq: int = 150) -> DataFrame:
    """Scores of furnace_refit() at each learner's best point of a smoothed grid; the frame is built once."""
    frame = furnace_frame(spark, sf_dir)
    grids = tuning.grid_together(*frame[:1], ks, d_confs, d_freq, "y", frame[1], CLASS_NAMES, LEARNERS)
    best = {learner: tuning.best(tuning.smooth(grid)) for learner, grid in grids.items()}
    return furnace_refit(spark, sf_dir, {learner: (r["k"], r["d_conf"]) for learner, r in best.items()}, d_freq=d_freq, frame=frame)[0]


#: Mixed classification sets by name: frame, key, categorical and continuous features, number of classes.
PUBLIC_LIKE = {
    "star": (frames.STAR, "l_orderkey", frames.STAR_CATEGORICAL, frames.STAR_CONTINUOUS, 2),
    "orders": (frames.ORDERS, "o_orderkey", frames.ORDER_CATEGORICAL, frames.ORDER_CONTINUOUS, 2),
    "texts": (f"SELECT t.*, quality AS y FROM ({frames.TEXTS}) t", "doc_id", frames.TEXT_CATEGORICAL, frames.TEXT_CONTINUOUS, 2),
    "parts": (frames.PARTS, "p_partkey", frames.PARTS_FEATURES, [], 4),
}
ENCODINGS = ("original", "label_plus_rules", "onehot", "onehot_plus_interactions")


def _encodings(packed: lockstep.Packed, columns: list[tuple[str, list[float] | None]], known: dict[str, list[str]], rules: list, train, test) -> tuple[lockstep.Design, dict[str, np.ndarray]]:
    """One design with everything that the encodings use, and each one's columns. columns: (name, cuts), a rule's ordinals count them."""
    of = {c: known[c] if x is None else tuning.interval_names(x) for c, x in columns}
    coded = [tuning.code_column(packed, c, x, of[c]) for c, x in columns]
    numbers = [("number", i) for i in range(len(packed.continuous))]
    slots = [("rule", [(packed.place(c), np.array([v == w for w in packed.table(c, x)]))]) for c, x in columns for v in of[c]]
    made, ends = coded + numbers + slots + [tuning.rule_column(packed, columns, r) for r in rules], np.cumsum([len(coded), len(numbers), len(slots), len(rules)])
    coded_, numbers_, slots_, rules_ = np.split(np.arange(len(made)), ends[:-1])
    pairs = rules_[[r["size"] == 2 for r in rules]] if rules else rules_
    used = {"original": [coded_, numbers_], "label_plus_rules": [coded_, numbers_, rules_], "onehot": [slots_, numbers_], "onehot_plus_interactions": [slots_, numbers_, pairs]}
    return lockstep.Design(made, frozenset(train), frozenset(test)), {m: np.concatenate(c) for m, c in used.items()}


def encodings_by_cross_validation(spark: SparkSession, sf_dir: str, name: str = "parts", folds: int = 5, ks=tuple(range(2, 11)), learners_=("logistic", "perceptron")) -> DataFrame:
    """(method, learner, metric, mean, deviation, std_error, runs, k): label codes and one-hot slots, each with and without what the rules add.

    The number of intervals is the one of least log-loss of label codes with rules, learnt without the first two folds and scored on the second; the first is not looked at.
    All folds share one table of codes at the finest cuts of any of them, one mining run, and the passes of their learners.
    """
    select, key, categorical, continuous, n_classes = PUBLIC_LIKE[name]
    df = frames.frame(spark, sf_dir, select)
    df = df.select(*categorical, *continuous, "y", F.col("y").cast("int").alias("label"), F.pmod(F.xxhash64(key), F.lit(folds)).cast("int").alias("fold"), held_out(key).alias("draw"))
    df = materialise(df, "cv")
    df = baselines.standardised(df, continuous) if continuous else df  # learners want one scale; cuts and rules don't see it
    b = params.suggest(len(categorical) + len(continuous), n_classes)
    attach.bounded(df, categorical)
    held = df.groupBy("fold").agg(F.max("label").alias("most"), *[F.collect_set(value_of(c)).alias(f"c{i}") for i, c in enumerate(categorical)]).collect()
    kept = lambda train: {c: sorted({v for r in held if r["fold"] in train for v in r[f"c{i}"]}) for i, c in enumerate(categorical)}
    parts = {f: [g for g in range(folds) if g != f] for f in range(folds)}
    apart = parts | ({folds: list(range(2, folds))} if continuous else {})  # number folds: where k is chosen
    values, many = kept(range(folds)), max(r["most"] for r in held) + 1
    binners = binning.fit_together(df, continuous, "label", many, "fold", apart, max(ks))
    edges = {c: sorted({x for m in binners.values() for x, _ in m.cuts.get(i, [])}) for i, c in enumerate(continuous, 1)}
    packed = lockstep.pack(df, "label", "fold", "draw", categorical, continuous, values, edges, many)
    binned = [*categorical, *(f"{c}_bin" for c in continuous)]
    counted = lockstep.cube(packed, [str(c) for c in range(many)], range(folds))

    def designs(asked: dict[int, tuple[int, int]], tests: dict[int, list[int]]):
        """Designs of (part, k) by number, with rules of one mining run."""
        cut = {i: binners[f].truncate(k) for i, (f, k) in asked.items()}
        columns = lambda i: [(c, None) for c in categorical] + [(c, [x for x, _ in cut[i].cuts[at]]) for at, c in enumerate(continuous, 1)]
        of = lambda f: df.where(F.col("fold").isin(apart[f]))
        frames_of = lambda: {i: cut[i].transform(of(f)) if continuous else of(f) for i, (f, _) in asked.items()}
        mined = tuning.mined_together(packed, counted, {i: (columns(i), apart[f]) for i, (f, _) in asked.items()}, b.d_freq, frames_of, "y", binned)
        rules = selectors.recut(mined, b.d_conf).features.orderBy("cv", "feature_id").collect()
        return [_encodings(packed, columns(i), kept(apart[f]), [r for r in rules if r["cv"] == i], apart[f], tests[i]) for i, (f, _) in asked.items()]

    k = 0
    if continuous:
        made = designs({k: (folds, k) for k in ks}, {k: [1] for k in ks})
        engine = lockstep.Lockstep(packed, [d for d, _ in made])
        models = [lockstep.Model(i, used["label_plus_rules"], "logistic") for i, (_, used) in enumerate(made)]
        got = engine.tally(models, engine.fit(models))
        k = min((tuning.measures(got[i])["log_loss"], k) for i, k in enumerate(ks) if i in got)[1]
    made = designs({f: (f, k) for f in parts}, {f: [f] for f in parts})
    engine = lockstep.Lockstep(packed, [d for d, _ in made])
    named = [(f, mode, learner) for f in parts for mode in ENCODINGS for learner in learners_]
    models = [lockstep.Model(f, made[f][1][mode], learner) for f, mode, learner in named]
    fitted = engine.fit(models)
    area, rows = engine.auc(models, fitted) if n_classes == 2 else {}, []
    for i, tally in engine.tally(models, fitted).items():
        scored = tuning.measures(tally) | ({"auc": area.get(i)} if n_classes == 2 else {})
        f, mode, learner = named[i]
        rows += [(mode, learner, metric, f, v) for metric, v in scored.items() if v is not None]  # no AUC without both classes
    scored = spark.createDataFrame(rows, "method string, learner string, metric string, fold int, score double")
    return evaluate.summarise(scored, ["method", "learner", "metric"]).withColumn("k", F.lit(k))


CELLS = 15


def regression_comparison(spark: SparkSession, sf_dir: str, splits: int = 3, d_freq: int = 2500, d_conf: int = 1225, k: int = 5, seed: int = 1, forest_trees: int = 50) -> DataFrame:
    """(method, mean, deviation, std_error, runs, terms): squared error over random two-thirds splits, of the base, the interaction baselines, and products found by rules.

    Customers fall into fifteen cells by a hash; a split trains on ten of them, and penalties are chosen over folds of those, all from matrices of products.
    """
    columns = frames.CUSTOMER_FEATURES
    df = baselines.standardised(frames.frame(spark, sf_dir, CUSTOMERS_WITHOUT_NULLS), columns).withColumn("cell", F.pmod(F.xxhash64("c_custkey"), F.lit(CELLS)).cast("int"))
    df = materialise(df, "customers")
    design = baselines.Design(df, columns, "response", "cell", CELLS)
    draw, tasks = random.Random(seed), []
    for s in range(splits):
        cells = draw.sample(range(CELLS), CELLS * 2 // 3)
        rest = [c for c in range(CELLS) if c not in cells]
        part = materialise(df.where(F.col("cell").isin(cells)), "train")

        def products(part=part) -> list[tuple[int, int]]:
            labelled = materialise(binning.quantile_classes(part, "response", 5, "c_custkey").withColumn("y", F.col("y").cast("string")), "quintiles")
            binned = binning.EntropyBinner(k, 20, columns, "y").fit(labelled).transform(labelled)
            found = selectors.select_nonredundant(binned, "y", [f"{c}_bin" for c in columns], d_freq, d_conf)
            return sorted((r["f1"], r["f2"]) for r in feature_ops.product_pairs(found.features).collect())

        def forest(part=part, rest=rest) -> tuple[float, int]:
            model = learners.forest("regression", forest_trees).fit(baselines.design(part, columns, [], "response"))
            test = baselines.design(df.where(F.col("cell").isin(rest)), columns, [], "response")
            return float(model.transform(test).agg(evaluate.mse("label", "prediction")).first()[0]), len(columns)

        methods = {
            "base": lambda cells=cells, rest=rest: baselines.main_effects(design, cells, rest), "iterated_lasso": lambda cells=cells, rest=rest: baselines.iterated(design, cells, rest),
            "screened_lasso": lambda cells=cells, rest=rest, part=part: baselines.screened(design, cells, rest, part), "backtracking": lambda cells=cells, rest=rest: baselines.backtracked(design, cells, rest),
            "hierarchical_lasso": lambda cells=cells, rest=rest, part=part: baselines.hierarchical(design, cells, rest, part), "reluctant_two_stage": lambda cells=cells, rest=rest, part=part: baselines.reluctant(design, cells, rest, part),
            "regression_splines": lambda cells=cells, rest=rest, part=part: baselines.splines(design, cells, rest, part), "rule_products": lambda cells=cells, rest=rest: baselines.with_pairs(design, cells, rest, products()), "forest": forest,
        }
        tasks += [lambda name=name, s=s, m=m: (name, s, *m()) for name, m in methods.items()]
    rows = spark.createDataFrame([(n, s, float(e), int(t)) for n, s, e, t in in_parallel(tasks)], "method string, split int, score double, terms int")
    return evaluate.summarise(rows, ["method"]).join(rows.groupBy("method").agg(F.avg("terms").alias("terms")), "method")


CUSTOMERS_WITHOUT_NULLS = f"SELECT * FROM ({frames.CUSTOMERS}) c WHERE response IS NOT NULL"


def vector_classification(spark: SparkSession, sf_dir: str, dims: int = 64, splits: int = 2, d_freq: int = 2500, d_conf: int = 1225, k: int = 5) -> DataFrame:
    """(method, mean, deviation, std_error, runs): misclassification of nine balanced classes from vectors, by the base, iterated fits, backtracking, a forest, and with all products of rules."""
    select, columns = frames.vectors(dims, signs=False)
    df = materialise(frames.frame(spark, sf_dir, select).withColumn("c", F.col("y").cast("double")), "vectors")

    def run(s: int) -> list[tuple]:
        part = F.pmod(F.xxhash64("vec_id", F.lit(s)), F.lit(3))
        train, test = df.where(part < 2), df.where(part == 2)
        binned = binning.EntropyBinner(k, 20, columns, "y").fit(train).transform(train)
        found = selectors.select_nonredundant(binned, "y", [f"{c}_bin" for c in columns], d_freq, d_conf)
        pairs = sorted((r["f1"], r["f2"]) for r in feature_ops.product_pairs(found.features).collect())
        out, made = [], {}

        def fitted(name: str, used: list, fitter=None):
            a, b = (tuning.compact(baselines.design(d, columns, used, "c").select("features", "label"), "design") for d in (train, test))
            model = (fitter or learners.logistic(a.count(), l1=False)).fit(a)
            out.append((name, s, float(model.transform(b).agg(evaluate.error_rate("label", "prediction")).first()[0])))
            made[name] = model

        fitted("base", [])
        strong = baselines.strongest(made["base"], len(columns), 20)
        fitted("iterated", list(combinations(sorted(strong), 2)))
        step = baselines.strongest(made["base"], len(columns), 8)
        fitted("backtracking", list(combinations(sorted(step), 2)))
        for more in (14, 20):  # each step lets the products of further strong features in
            step = sorted(set(step) | set(baselines.strongest(made["backtracking"], len(columns), more)))
            out.pop()
            fitted("backtracking", list(combinations(step, 2)))
        fitted("rule_products", pairs)
        fitted("forest", [], learners.forest())
        return out

    rows = spark.createDataFrame([r for one in in_parallel([lambda s=s: run(s) for s in range(splits)], 2) for r in one], "method string, split int, score double")
    return evaluate.summarise(rows, ["method"])


def step_costs(spark: SparkSession, sf_dir: str, p: int = 20, d_freq: int = 45, d_conf: int = 5) -> DataFrame:
    return complexity.observe(frames.frame(spark, sf_dir, frames.planted(p)), "y", _xs(p), d_freq, d_conf)


WORKLOADS = {f.__name__: f for f in (frequency_estimates, run_times, planted_rule_frequency, planted_prediction, furnace_grid, furnace_refit, encodings_by_cross_validation, regression_comparison, vector_classification, step_costs)}
