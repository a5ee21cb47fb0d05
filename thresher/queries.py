"""Registered queries of the split searches, and the SQL that checks them."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import encode, losses
from .operators import baseline, candidates, categorical, classification, curves, gini, histogram, metrics, mpc, regression, relations, sampling, tree
from .operators.domain import Domain, resolve
from .operators.held import hold, release
from .operators.ledger import Ledger
from .sources import workloads as W
from .sources.tables import shared_folder, table
from .streaming import splits as stream_splits

Query = Callable[[SparkSession, str], DataFrame]
KEYS = list(W.LINE_KEYS)
FIXED_SPLITS = [500_000, 2_000_000, 3_999_822, 4_000_000, 7_500_000, 9_999_999]
EPS, SEED = 0.05, 7
#: The quadratic baseline meets every row with every candidate, of which there are 1 / eps.
NAIVE_EPS = 0.5
#: Range edges in cents for the heavy and light test.
RANGES = [(1, 100_000), (1, 1_000_000), (1_000_001, 1_020_000), (4_000_000, 6_000_000), (1, 10_500_000)]


def _named(df: DataFrame, **names: str) -> DataFrame:
    return df.select(*[F.col(c).alias(names.get(c, c)) for c in df.columns])


def _curve(df: DataFrame, digits: int = 4) -> DataFrame:
    return df.select(F.col("x").alias("j"), "n_left", "n_right", F.round("loss", digits).alias("loss"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves.exact_split(W.planted(spark, sf_dir))


def reg_bound(spark: SparkSession, sf_dir: str, workload, eps: float, scale: int = 1) -> DataFrame:
    obs = hold(workload(spark, sf_dir))
    d = resolve(obs)
    got = regression.additive_split(obs, keys_of(obs), eps, d, scale, seed=SEED)
    return regression.bound_row(got, curves.exact_split(obs, "mse", scale), F.col("opt") + 0.625 * eps * (d.spread / scale) ** 2)


def _ratio_bound(obs: DataFrame, got: DataFrame, criterion: str, eps: float, scale: int = 1) -> DataFrame:
    return regression.bound_row(got, curves.exact_split(obs, criterion, scale), F.col("opt") * (1 + eps))


def _mult(mode: str, workload=W.planted, scale: int = 1, eps: float = 0.5) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        obs = hold(workload(spark, sf_dir))
        return _ratio_bound(obs, regression.multiplicative_split(obs, eps, scale=scale, mode=mode), "mse", eps, scale)

    return run


def _cls_mult(mode: str, workload=W.planted_class, eps: float = 0.2) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        obs = hold(workload(spark, sf_dir))
        return _ratio_bound(obs, classification.multiplicative_split(obs, eps, mode=mode), "misclassification", eps)

    return run


def _frontier(criterion: str, workload, eps: float) -> Query:
    """The split itself: the frontier search has a closed form, which SQL repeats."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        obs = hold(workload(spark, sf_dir))
        d = resolve(obs)
        if criterion == "mse":
            grid = [0.0, *[0.5 * 2.0**k for k in range(120) if 0.5 * 2.0 ** (k - 1) < d.m * d.spread**2]]
            return regression.multiplicative_split(obs, eps, d, mode="frontier", grid=grid).select("j", "loss", "n_left", "n_right")
        grid = [0.0, *[2.0**k for k in range(60) if 2.0 ** (k - 1) < d.m]]
        return classification.multiplicative_split(obs, eps, d, mode="frontier", grid=grid).select("j", "loss", "n_left", "n_right")

    return run


def cls_additive(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    obs = W.planted_class(spark, sf_dir)
    return classification.additive_split(obs, KEYS, EPS, rate_kind=kind, seed=SEED, kind="lcg").select("j", "loss")


def additive_bound(spark: SparkSession, sf_dir: str, workload, eps: float, criterion: str = "misclassification", estimator: str = "plugin", **options) -> DataFrame:
    obs = hold(workload(spark, sf_dir, **options))
    keys = keys_of(obs)
    got = classification.additive_split(obs, keys, eps, seed=SEED) if criterion == "misclassification" else gini.additive_split(obs, keys, eps, estimator=estimator, seed=SEED)
    true = candidates.losses(obs, [got.first()["j"]], criterion)
    return regression.bound_row(true, curves.exact_split(obs, criterion), F.col("opt") + (eps if estimator == "plugin" else 4 * eps))


def cat_additive(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "lineitem").withColumns({"x": W.price_cents(), "y": encode.to_pm1(F.col("l_quantity") > 25)})
    m, n = df.agg(F.count("*"), F.countDistinct("l_partkey")).first()
    return categorical.loss_of(categorical.additive_split(df, "l_partkey", "y", KEYS, 0.2, n, m, seed=SEED, kind="lcg"))


def range_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    obs = W.price_qty(spark, sf_dir)
    d = resolve(obs)
    return sampling.range_count(obs, KEYS, RANGES, 0.5, d.n, d.m, seed=SEED, kind="lcg").select("lo", "hi", "sampled", "heavy", "light")


def mpc_reg_additive(spark: SparkSession, sf_dir: str, workload=W.planted) -> DataFrame:
    obs = hold(workload(spark, sf_dir))
    d = resolve(obs)
    got = mpc.regression_additive(obs, keys_of(obs), d, seed=SEED)
    return regression.bound_row(got, curves.exact_split(obs), F.col("opt") + 0.625 * d.spread**2 / math.sqrt(d.m))


def mpc_cls_additive(spark: SparkSession, sf_dir: str, rate_kind: str, allowed: float) -> DataFrame:
    """``eps2`` samples enough for the stated 1 / sqrt(m); what the printed rate reaches is some times that (README)."""
    obs = hold(W.planted_class(spark, sf_dir))
    d = resolve(obs)
    j = mpc.classification_additive(obs, KEYS, d, rate_kind, seed=SEED).first()["j"]
    return regression.bound_row(candidates.losses(obs, [j], "misclassification"), curves.exact_split(obs, "misclassification"), F.col("opt") + allowed / math.sqrt(d.m))


def mpc_gini(spark: SparkSession, sf_dir: str, estimator: str = "plugin") -> DataFrame:
    obs = hold(W.planted_class(spark, sf_dir))
    d = resolve(obs)
    j = mpc.gini_additive(obs, KEYS, d, estimator, seed=SEED).first()["j"]
    return regression.bound_row(candidates.losses(obs, [j], "gini"), curves.exact_split(obs, "gini"), F.col("opt") + d.m**-0.25)


def mpc_evaluator(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _curve(mpc.evaluate_splits(W.planted(spark, sf_dir), KEYS, FIXED_SPLITS))


def mpc_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each massively parallel search keeps to the model's rounds, memory and messages; the bounds are spelled out here."""
    obs, label = hold(W.planted(spark, sf_dir)), hold(W.planted_class(spark, sf_dir))
    d, dc = resolve(obs), resolve(label)
    levels = regression.guesses.levels_for(d.n, 0.5)
    batches = -(-(d.n.bit_length() + 1) // levels)
    log = 9 * math.log(d.n)
    runs = {
        "regression additive": (lambda led: mpc.regression_additive(obs, KEYS, d, seed=SEED, ledger=led), d, 1 + mpc.SORT_ROUNDS + 2),
        "regression multiplicative": (lambda led: mpc.regression_multiplicative(obs, KEYS, 0.5, 0.5, d, mode="frontier", ledger=led), d, mpc.SORT_ROUNDS + 2 * (batches + 2)),
        "classification additive": (lambda led: mpc.classification_additive(label, KEYS, dc, seed=SEED, ledger=led), dc, 1),
        "gini additive": (lambda led: mpc.gini_additive(label, KEYS, dc, seed=SEED, ledger=led), dc, 1),
        "classification multiplicative": (lambda led: mpc.classification_multiplicative(label, KEYS, 0.5, 0.5, dc, mode="frontier", ledger=led), dc, mpc.SORT_ROUNDS + 2 * (batches + 2)),
    }
    rows = []
    for name, (run, dom, rounds) in runs.items():
        led = Ledger()
        run(led).collect()
        led.finish()
        splits = led.broadcast_rows
        root = math.sqrt(dom.m)
        sent_ok = led.messages <= max(splits + 1 + 2 * led.machines, 2 * log * root)
        rows.append((name, led.machines == round(root), led.rounds <= rounds, led.machine_words <= 8 * root + splits + 2 * log * root, sent_ok))
    return spark.createDataFrame(rows, "method string, machines_ok boolean, rounds_ok boolean, memory_ok boolean, messages_ok boolean")


def stump_multi_attr(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = W.line_features(spark, sf_dir)
    return tree.per_attribute(df, FEATURES, "y", "mse", 100, 2)


def _tree_rows(df: DataFrame, features: list[str], scale: int, digits: int) -> DataFrame:
    found = tree.splits_of(tree.grow(hold(df), features, "y", "mse", 2, scale=scale, digits=digits))
    return df.sparkSession.createDataFrame(found, "node int, attr string, j long, loss double, n long")


def tree_depth2(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("key"), F.col("p_size").cast("long").alias("size"), encode.fixed_point("p_retailprice").alias("y"))
    return _tree_rows(df, ["key", "size"], 100, 4)


def tree_star_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two levels over five attributes of lineitem, orders and part."""
    return _tree_rows(W.line_features(spark, sf_dir), FEATURES, 100, 2)


def tree_predictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows, error and squared error of a depth-2 tree on the conversations, applied as nested conditions."""
    df = hold(W.conversation(spark, sf_dir))
    grown = tree.grow(df, ["x"], "y", "misclassification", 2)
    return tree.score(tree.predict(df, grown), "y").select((F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")).alias("n"), F.round("error", 6).alias("error"))


def stump_conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A depth-1 tree as a weak classifier."""
    grown = tree.stump(hold(W.conversation(spark, sf_dir)), ["x"], "y")
    return spark.createDataFrame(tree.splits_of(grown), "node int, attr string, j long, loss double, n long")


def emb_best_dim(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = W.embedding_features(spark, sf_dir)
    curve = curves.curve_of(e.groupBy("attr", "x").agg(F.count_if(F.col("y") > 0).alias("pos"), F.count_if(F.col("y") <= 0).alias("neg")), "gini", 1, ["attr"])
    return curve.select("attr", F.col("x").alias("j"), F.round("loss", 6).alias("loss")).orderBy("loss", "attr", "j").limit(1)


def sample_bernoulli(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.bernoulli(table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), ["o_orderkey"], 0.1, SEED, "lcg")


def sample_bottom_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.bottom_k(table(spark, sf_dir, "orders").select("o_orderkey"), ["o_orderkey"], 100, SEED, "lcg").select("o_orderkey", F.col("_h").alias("h"))


def gini_paired(spark: SparkSession, sf_dir: str) -> DataFrame:
    obs = W.conversation(spark, sf_dir)
    return gini.paired_terms(obs, ["conv_id", "turn"], 0.3, Domain(0, 1000, -1, 1), seed=SEED, kind="lcg").select("j", "label", "side", F.round("est", 6).alias("est"))


def gini_additive(spark: SparkSession, sf_dir: str) -> DataFrame:
    obs = W.conversation(spark, sf_dir)
    return gini.additive_split(obs, ["conv_id", "turn"], 0.3, Domain(0, 1000, -1, 1), seed=SEED, kind="lcg")


def gini_plugin(spark: SparkSession, sf_dir: str) -> DataFrame:
    obs = W.conversation(spark, sf_dir)
    return gini.additive_split(obs, ["conv_id", "turn"], 0.3, Domain(0, 1000, -1, 1), estimator="plugin", seed=SEED, kind="lcg")


def stream_window_split(spark: SparkSession, sf_dir: str, criterion: str = "misclassification") -> DataFrame:
    path = f"{sf_dir}/events.parquet*"
    schema = spark.read.parquet(path).schema
    events = spark.readStream.schema(schema).parquet(path)
    at = F.col("ts").cast("timestamp")
    if criterion == "mse":
        # The hour of the day against the value: a split of each day.
        obs, scale = events.select(at.alias("ts"), (F.hour(at) + 1).cast("long").alias("x"), encode.fixed_point("value").alias("y")), (100, 2)
    else:
        obs, scale = events.select(at.alias("ts"), encode.fixed_point("value").alias("x"), encode.to_pm1(F.col("event_type") == "purchase").alias("y")), ()
    windowed = stream_splits.windowed_histogram(obs, "ts", "1 day", criterion)
    hist = stream_splits.run_to_table(windowed, shared_folder(spark, "stream-windows"), shared_folder(spark, "stream-checkpoint"))
    return stream_splits.window_splits(hist, criterion, *scale).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "j", "loss", "n")


def _cost_runs(obs: DataFrame, d: Domain) -> dict:
    return {
        "additive": lambda led: regression.additive_split(obs, KEYS, 0.01, d, seed=SEED, ledger=led, digits=9),
        "sequential": lambda led: regression.multiplicative_split(obs, 0.5, d, mode="sequential", ledger=led, digits=9),
        "batched": lambda led: regression.multiplicative_split(obs, 0.5, d, mode="batched", ledger=led, digits=9),
        "frontier": lambda led: regression.multiplicative_split(obs, 0.5, d, mode="frontier", ledger=led, digits=9),
    }


def costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every account of each search, and its loss against the optimum, on the planted step. Times are this run's."""
    obs = hold(W.planted(spark, sf_dir))
    d = resolve(obs)
    best = curves.exact_split(obs, digits=9).first()["loss"]
    rows = []
    for name, run in _cost_runs(obs, d).items():
        led = Ledger()
        got = run(led).first()["loss"]
        r = led.finish().report()
        rows.append((name, r["passes"], r["rounds"], r["state_words"], r["sample_rows"], r["live_guesses"], r["comparisons"], r["update_ns"], r["post_ms"], round(metrics.excess(got, best), 9), round(metrics.ratio(got, best), 9)))
    return spark.createDataFrame(rows, "method string, passes int, rounds int, state_words long, sample_rows long, live_guesses int, comparisons int, update_ns long, post_ms long, excess double, ratio double")


def cost_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether passes, state and quality of each search keep to what the method promises."""
    obs = hold(W.planted(spark, sf_dir))
    d = resolve(obs)
    best = curves.exact_split(obs, digits=9).first()["loss"]
    levels, deep, grid = regression.guesses.levels_for(d.n, 0.5), d.n.bit_length() + 1, len(regression.error_grid(d, 0.5))
    passes = {"additive": 2, "sequential": deep, "batched": -(-deep // levels) + 1, "frontier": -(-deep // levels) + 1}
    probes = {"additive": 4 * 9 * math.log(d.n) / 0.01, "sequential": grid**2, "batched": grid**2 * 2 ** (levels + 1), "frontier": 2 * grid * 2 ** (levels + 1)}
    rows = []
    for name, run in _cost_runs(obs, d).items():
        led = Ledger()
        got = run(led).first()["loss"]
        allowed = best + 0.625 * 0.01 * d.spread**2 if name == "additive" else 1.5 * best
        rows.append((name, led.passes <= passes[name], led.broadcast_rows <= probes[name], got <= allowed + 1e-9))
    return spark.createDataFrame(rows, "method string, passes_ok boolean, space_ok boolean, quality_ok boolean")


def success_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The additive search's excess on the planted step for twenty seeds, against the promised bound."""
    obs = hold(W.planted(spark, sf_dir))
    d = resolve(obs)
    return metrics.success_over_seeds(obs, KEYS, 0.1, SEEDS, 0.625 * 0.1 * d.spread**2, d, kind="lcg")


def gini_term_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the paired estimates of all four terms stay within eps of the truth, by eps."""
    obs = hold(W.planted_class(spark, sf_dir))
    rows = []
    for eps in (0.4, 0.2, 0.1):
        terms = gini.paired_terms(obs, KEYS, eps, seed=SEED)
        rows.append((eps, metrics.term_error(terms, obs).first()["worst"] <= eps))
    return spark.createDataFrame(rows, "eps double, within boolean")


def gini_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    sample = sampling.bottom_k(W.conversation(spark, sf_dir), ["conv_id", "turn"], 200, SEED, "lcg")
    return gini.coverage(sample, 1000, 0.3)


def sample_adaptive(spark: SparkSession, sf_dir: str) -> DataFrame:
    sample, p = sampling.adaptive(table(spark, sf_dir, "orders").select("o_orderkey"), ["o_orderkey"], 500, SEED, "lcg")
    return sample.select("o_orderkey", F.lit(p).alias("p"))


def quantile_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each of 16 approximate quantile bins of order totals holds its share within the accuracy asked for."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    m = orders.count()
    counts = encode.quantile(orders, "o_totalprice", 16).groupBy("x").agg(F.count("*").alias("n"))
    return counts.select("x", (F.abs(F.col("n") / m - 1 / 16) <= 0.005).alias("balanced"))


def cat_bound(spark: SparkSession, sf_dir: str, name: str, rate_kind: str) -> DataFrame:
    """The true loss of the grouping that a sample suggests, against the optimum plus eps."""
    df, cat, keys = CATEGORIES[name](spark, sf_dir)
    df = hold(df)
    m, n = df.agg(F.count("*"), F.countDistinct(cat)).first()
    split = categorical.additive_split(df, cat, "y", keys, CAT_EPS, n, m, rate_kind=rate_kind, seed=SEED)
    return regression.bound_row(categorical.loss_on(df, split, cat, "y"), categorical.loss_of(categorical.exact_split(df, cat, "y")), F.col("opt") + CAT_EPS)


def _lines_with_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").withColumns({"x": W.price_cents(), "y": encode.to_pm1(F.col("l_quantity") > 25), "flag": F.concat("l_returnflag", "l_linestatus")})


CAT_EPS = 0.1
#: Categorical workloads: (rows, category, row keys).
CATEGORIES: dict[str, Callable] = {
    "source": lambda spark, sf: (W.doc_label(spark, sf), "source", ["doc_id"]),
    "lang": lambda spark, sf: (W.doc_label(spark, sf, "toxic"), "lang", ["doc_id"]),
    "flag": lambda spark, sf: (_lines_with_class(spark, sf).select("flag", "y", *KEYS), "flag", KEYS),
    "brand": lambda spark, sf: (table(spark, sf, "part").select("p_brand", "p_partkey", encode.to_pm1(F.col("p_size") > 25).alias("y")), "p_brand", ["p_partkey"]),
    "partkey": lambda spark, sf: (_lines_with_class(spark, sf).select("l_partkey", "l_orderkey", "l_linenumber", "l_suppkey", "x", "y"), "l_partkey", KEYS),
}
SEEDS = list(range(1, 21))
FEATURES = ["qty", "discount", "tax", "order_day", "size"]
#: Regression workloads by name: (observations, scale).
REGRESSIONS = {"qty": (W.qty, 100), "price_qty": (W.price_qty, 1), "ship": (W.ship_discount, 100), "orders": (W.order_total, 100), "events": (W.event_value, 100), "part": (W.part, 100), "doc_words": (W.doc_words, 1)}
#: Classification workloads by name: (observations, options).
CLASSES = {"price": (W.price_class, {}), "ship": (W.ship_class, {}), "quality": (W.doc_label, {"label": "quality"}), "toxic": (W.doc_label, {"label": "toxic"}), "events": (W.event_class, {}), "conv": (W.conversation, {})}


def keys_of(obs: DataFrame) -> list[str]:
    """The columns that tell rows apart; lines of an order need the attribute too."""
    keys = [c for c in obs.columns if c not in ("x", "y", "source", "lang")]
    return [*keys, "x"] if "l_linenumber" in keys else keys


def _grid() -> dict[str, Query]:
    """Every approximate method on the workloads that the survey gives it."""
    found: dict[str, Query] = {}
    for name in ("qty", "ship", "part", "doc_words"):
        workload, scale = REGRESSIONS[name]
        found[f"reg_additive_bound_{name}"] = lambda spark, sf, w=workload, s=scale: reg_bound(spark, sf, w, 0.03, s)
    for name in ("qty", "price_qty", "orders", "events"):
        workload, scale = REGRESSIONS[name]
        found[f"reg_mult_bound_{name}"] = _mult("frontier", workload, scale)
    for name in ("ship", "quality", "toxic", "events", "conv"):
        workload, options = CLASSES[name]
        found[f"cls_additive_bound_{name}"] = lambda spark, sf, w=workload, o=options: additive_bound(spark, sf, w, EPS, **o)
    for name in ("price", "ship", "quality", "toxic", "conv"):
        workload, options = CLASSES[name]
        found[f"gini_bound_{name}"] = lambda spark, sf, w=workload, o=options: additive_bound(spark, sf, w, 0.1, "gini", "plugin", **o)
    for name in ("price", "quality", "toxic", "conv"):
        workload, options = CLASSES[name]
        found[f"cls_mult_bound_{name}"] = _cls_mult("frontier", lambda spark, sf, w=workload, o=options: w(spark, sf, **o))
    for eps in (0.4, 0.2, 0.1):
        found[f"gini_paired_bound_{round(100 * eps)}"] = lambda spark, sf, e=eps: additive_bound(spark, sf, W.conversation, e, "gini", "paired")
    for name in CATEGORIES:
        for kind in ("printed", "eps2"):
            found[f"cat_bound_{name}_{kind}"] = lambda spark, sf, n=name, k=kind: cat_bound(spark, sf, n, k)
    return found


def _released(query: Query) -> Query:
    """What the query before kept is let go first."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        release()
        return query(spark, sf_dir)

    return run


def _exact(workload, criterion: str = "mse", scale: int = 1, digits: int = 6) -> Query:
    return lambda spark, sf: curves.exact_split(workload(spark, sf), criterion, scale, digits)


def _additive_planted(method: str | None, eps: float = EPS) -> Query:
    return lambda spark, sf: regression.additive_split(W.planted(spark, sf), KEYS, eps, seed=SEED, kind="lcg", method=method)


def _losses(method: str) -> Query:
    return lambda spark, sf: _curve(candidates.losses(W.planted(spark, sf), FIXED_SPLITS, method=method))


def _loss_only(workload, criterion: str = "mse", scale: int = 1, digits: int = 6, **options) -> Query:
    """Workloads whose attribute says nothing: many splits tie, so only the least loss is compared."""
    return lambda spark, sf: curves.exact_split(workload(spark, sf, **options), criterion, scale, digits).select("loss", (F.col("n_left") + F.col("n_right")).alias("n"))


def unsampled_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    obs = W.price_qty(spark, sf_dir)
    return relations.without(obs, sampling.bernoulli(obs, KEYS, 0.5, SEED, "lcg"), "x")


def price_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each order with the last step of a price list at or below its total: an as-of join."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", encode.fixed_point("o_totalprice").alias("cents"))
    steps = spark.range(0, 200).select((F.col("id") * 500_000).alias("cents"), F.col("id").alias("step"))
    return relations.as_of(orders, steps, "cents", "step").groupBy("step").agg(F.count("*").alias("n"))


def segment_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared error of one leaf of balances, which may be negative, by segment and nation: mergeable sums under cube."""
    rows = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    by = ["c_mktsegment", "n_regionkey"]
    cubed = histogram.aggregate_over(rows.cube(*by), by, "mse", encode.shift(encode.fixed_point("c_acctbal"), -100_000))
    name = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("all")).alias(c)
    return cubed.select(name("c_mktsegment"), name("n_regionkey"), "n", F.round(losses.sse(F.col("n"), F.col("s"), F.col("q")) / F.col("n") / 10000.0, 2).alias("loss"))


def split_by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best split of supplier balances by key, for each region."""
    rows = table(spark, sf_dir, "supplier").join(table(spark, sf_dir, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    df = rows.select("r_name", F.col("s_suppkey").alias("key"), encode.fixed_point("s_acctbal").alias("y"))
    return tree.best_split(df, ["key"], "y", "mse", 100, ["r_name"], 2).select("r_name", "j", "loss")


def page_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of a page against whether its address is long: one more attribute source."""
    pages = table(spark, sf_dir, "pages").select(F.length("html").cast("long").alias("x"), encode.to_pm1(F.length("url") > 30).alias("y"))
    return curves.exact_split(pages, "gini").select("loss", (F.col("n_left") + F.col("n_right")).alias("n"))


def queries() -> dict[str, Query]:
    found = _named_queries() | _grid()
    return {name: _released(query) for name, query in found.items()}


def _named_queries() -> dict[str, Query]:
    return {
        "reg_exact_planted": _exact(W.planted),
        "reg_exact_qty": _exact(W.qty, "mse", 100, 2),
        "reg_exact_part": _exact(W.part, "mse", 100, 4),
        "reg_exact_doc_words": _exact(W.doc_words, "mse", 1, 4),
        "reg_curve_qty": lambda spark, sf: _curve(curves.loss_curve(W.qty(spark, sf), "mse", 100), 1),
        "reg_curve_part": lambda spark, sf: _curve(curves.loss_curve(W.part(spark, sf), "mse", 100)),
        "reg_brute_qty": lambda spark, sf: _curve(baseline.brute_force(W.qty(spark, sf), None, "mse", 100), 1),
        "reg_offline_part": lambda spark, sf: baseline.offline(W.part(spark, sf), "mse", 100, 4),
        "reg_additive_planted": _additive_planted("bsearch"),
        "reg_additive_arrow_planted": _additive_planted("arrow"),
        "reg_additive_merge_planted": _additive_planted("merge"),
        "reg_additive_coarse_planted": _additive_planted(None, NAIVE_EPS),
        "reg_additive_naive_planted": _additive_planted("naive", NAIVE_EPS),
        "reg_additive_bound": lambda spark, sf: reg_bound(spark, sf, W.planted, 0.03),
        "reg_additive_bound_noise": lambda spark, sf: reg_bound(spark, sf, W.price_qty, 0.03),
        "reg_multi_losses": _losses("bsearch"),
        "reg_multi_losses_arrow": _losses("arrow"),
        "reg_multi_losses_merge": _losses("merge"),
        "reg_multi_losses_two_pass": _losses("two_pass"),
        "reg_mult_seq": _mult("sequential"),
        "reg_mult_batched": _mult("batched"),
        "reg_mult_batched_part": _mult("batched", W.part, 100),
        "reg_mult_frontier": _frontier("mse", W.planted, 1.0),
        "cls_exact_planted": _exact(W.planted_class, "misclassification"),
        "cls_exact_conv": _exact(W.conversation, "misclassification"),
        "gini_exact_planted": _exact(W.planted_class, "gini"),
        "gini_exact_conv": _exact(W.conversation, "gini"),
        "entropy_exact_conv": _exact(W.conversation, "entropy"),
        "cls_additive_planted": lambda spark, sf: cls_additive(spark, sf, "eps2"),
        "cls_additive_printed": lambda spark, sf: cls_additive(spark, sf, "printed"),
        "cls_additive_bound": lambda spark, sf: additive_bound(spark, sf, W.price_class, EPS),
        "gini_paired_terms": gini_paired,
        "gini_additive": gini_additive,
        "gini_plugin": gini_plugin,
        "gini_additive_bound": lambda spark, sf: additive_bound(spark, sf, W.planted_class, 0.1, "gini", "paired"),
        "cls_mult_seq": _cls_mult("sequential"),
        "cls_mult_batched": _cls_mult("batched"),
        "cls_mult_frontier": _frontier("misclassification", W.planted_class, 1.0),
        "cat_exact_brand": lambda spark, sf: categorical.loss_of(categorical.exact_split(table(spark, sf, "part").withColumn("y", encode.to_pm1(F.col("p_size") > 25)), "p_brand", "y")),
        "cat_exact_source": lambda spark, sf: categorical.exact_split(W.doc_label(spark, sf), "source", "y"),
        "cat_enumerate_flag": lambda spark, sf: categorical.enumerate_split(table(spark, sf, "lineitem").select(F.concat("l_returnflag", "l_linestatus").alias("c"), encode.to_pm1(F.col("l_quantity") > 25).alias("y")), "c", "y"),
        "cat_additive_partkey": cat_additive,
        "disj_yes": lambda spark, sf: categorical.is_separable(categorical.disjointness_stream(*W.user_sets(spark, sf, False), "user_id")),
        "disj_no": lambda spark, sf: categorical.is_separable(categorical.disjointness_stream(*W.user_sets(spark, sf, True), "user_id")),
        "range_count": range_count,
        "mpc_reg_additive": mpc_reg_additive,
        "mpc_reg_additive_noise": lambda spark, sf: mpc_reg_additive(spark, sf, W.price_qty),
        "mpc_reg_mult": lambda spark, sf: _ratio_bound(o := hold(W.part(spark, sf)), mpc.regression_multiplicative(o, ["p_partkey"], 0.5, 0.5, scale=100), "mse", 0.5, 100),
        "mpc_reg_mult_noise": lambda spark, sf: _ratio_bound(o := hold(W.price_qty(spark, sf)), mpc.regression_multiplicative(o, KEYS, 0.5, 0.5, mode="frontier"), "mse", 0.5),
        "mpc_cls_additive": lambda spark, sf: mpc_cls_additive(spark, sf, "eps2", 1.0),
        "mpc_cls_additive_printed": lambda spark, sf: mpc_cls_additive(spark, sf, "printed", 5.0),
        "mpc_gini": mpc_gini,
        "mpc_gini_paired": lambda spark, sf: mpc_gini(spark, sf, "paired"),
        "mpc_cls_mult": lambda spark, sf: _ratio_bound(o := hold(W.conversation(spark, sf)), mpc.classification_multiplicative(o, ["conv_id", "turn"], 0.2), "misclassification", 0.2),
        "mpc_evaluator": mpc_evaluator,
        "mpc_costs": mpc_costs,
        "stump_multi_attr": stump_multi_attr,
        "stump_conv": stump_conv,
        "tree_depth2": tree_depth2,
        "tree_star_join": tree_star_join,
        "tree_predictions": tree_predictions,
        "emb_best_dim": emb_best_dim,
        "no_split_rollup": lambda spark, sf: baseline.no_split_rollup(table(spark, sf, "part").select("p_type", "p_brand", encode.fixed_point("p_retailprice").alias("y")), "y", ["p_type", "p_brand"], 100, 4),
        "sample_bernoulli": sample_bernoulli,
        "sample_bottom_k": sample_bottom_k,
        "encode_rank": lambda spark, sf: encode.dense_rank(table(spark, sf, "orders").select("o_orderkey", "o_orderdate"), "o_orderdate").select("o_orderkey", "x"),
        "encode_quantile": quantile_bins,
        "sample_adaptive": sample_adaptive,
        "stream_window_split": stream_window_split,
        "stream_window_regression": lambda spark, sf: stream_window_split(spark, sf, "mse"),
        "search_costs": costs,
        "search_cost_bounds": cost_bounds,
        "success_over_seeds": success_rates,
        "gini_term_errors": gini_term_errors,
        "gini_coverage": gini_coverage,
        "figure_regression": lambda spark, sf: curves.exact_split(W.figure_regression(spark)),
        "figure_classification": lambda spark, sf: curves.exact_split(W.figure_classification(spark), "misclassification"),
        "figure_gini": lambda spark, sf: curves.exact_split(W.figure_classification(spark), "gini"),
        "value_gaps": lambda spark, sf: baseline.value_gaps(W.qty(spark, sf)),
        "value_gaps_part": lambda spark, sf: baseline.value_gaps(W.price_qty(spark, sf)),
        "reg_loss_ship": _loss_only(W.ship_discount, "mse", 100, 6),
        "reg_loss_orders": _loss_only(W.order_total, "mse", 100, 0),
        "reg_loss_events": _loss_only(W.event_value, "mse", 100, 3),
        "cls_loss_price": _loss_only(W.price_class, "misclassification"),
        "cls_loss_ship": _loss_only(W.ship_class, "misclassification"),
        "cls_loss_events": _loss_only(W.event_class, "misclassification"),
        "cls_loss_quality": _loss_only(W.doc_label, "misclassification"),
        "gini_loss_toxic": _loss_only(W.doc_label, "gini", label="toxic"),
        "labelled_docs": lambda spark, sf: relations.labelled(table(spark, sf, "documents").select("doc_id", "n_chars"), table(spark, sf, "labels"), "doc_id"),
        "unlabelled_docs": lambda spark, sf: relations.unlabelled(table(spark, sf, "documents").select("doc_id", "n_chars"), table(spark, sf, "labels"), "doc_id"),
        "disj_shared_users": lambda spark, sf: relations.shared(*W.user_sets(spark, sf, False), "user_id"),
        "unsampled_values": unsampled_values,
        "as_of_price_steps": price_steps,
        "no_split_cube": segment_cube,
        "split_by_region": split_by_region,
        "page_lengths": page_lengths,
    }


# --- SQL ---------------------------------------------------------------------------------------

_NOISE = "(l_orderkey * 7919 + l_linenumber * 104729)"
_CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"
_LINE = "l_orderkey, l_linenumber, l_partkey, l_suppkey"
OBS = {
    "planted": f"SELECT {_CENTS} AS x, CAST((CASE WHEN l_extendedprice <= 40000 THEN 10 ELSE 30 END) + {_NOISE} % 20 AS BIGINT) AS y, {_LINE} FROM lineitem",
    "qty": f"SELECT CAST(l_quantity AS BIGINT) AS x, {_CENTS} AS y FROM lineitem",
    "price_qty": f"SELECT {_CENTS} AS x, CAST(l_quantity AS BIGINT) AS y, {_LINE} FROM lineitem",
    "part": "SELECT p_partkey AS x, CAST(round(p_retailprice * 100) AS BIGINT) AS y FROM part",
    "doc_words": "SELECT n_chars AS x, CAST(len(string_split(text, ' ')) AS BIGINT) AS y FROM documents",
    "price_class": f"SELECT {_CENTS} AS x, CASE WHEN l_quantity > 25 THEN 1 ELSE -1 END AS y, {_LINE} FROM lineitem",
    "planted_class": f"SELECT {_CENTS} AS x, CASE WHEN (l_extendedprice <= 40000) = ({_NOISE} % 100 < 80) THEN 1 ELSE -1 END AS y, {_LINE} FROM lineitem",
    "conversation": "SELECT CAST(length(text) + 1 AS BIGINT) AS x, CASE WHEN role = 'assistant' THEN 1 ELSE -1 END AS y, conv_id, turn FROM conversations WHERE role <> 'system' AND text IS NOT NULL",
}
_SSE = "CASE WHEN {n} > 0 THEN greatest(CAST({q} AS DOUBLE) - CAST({s} AS DOUBLE) * CAST({s} AS DOUBLE) / CAST({n} AS DOUBLE), 0) ELSE 0 END"
_SIDE = {
    "misclassification": "CAST(least({p}, {g}) AS DOUBLE)",
    "gini": "CASE WHEN {p} + {g} > 0 THEN CAST({p} + {g} AS DOUBLE) - (CAST({p} AS DOUBLE) * {p} + CAST({g} AS DOUBLE) * {g}) / CAST({p} + {g} AS DOUBLE) ELSE 0 END",
    "entropy": "(CASE WHEN {p} > 0 THEN -CAST({p} AS DOUBLE) * log2(CAST({p} AS DOUBLE) / ({p} + {g})) ELSE 0 END) + (CASE WHEN {g} > 0 THEN -CAST({g} AS DOUBLE) * log2(CAST({g} AS DOUBLE) / ({p} + {g})) ELSE 0 END)",
}


def curve_sql(obs: str, criterion: str = "mse", scale: int = 1, by: str = "") -> str:
    """CTEs ending in ``curve``: x, n_left, n_right, err_left, err_right, loss, predictions."""
    part, key = (f"PARTITION BY {by} ", f"{by}, ") if by else ("", "")
    if criterion == "mse":
        agg = "count(*) AS n, sum(CAST(y AS HUGEINT)) AS s, sum(CAST(y AS HUGEINT) * y) AS q"
        cols = ("n", "s", "q")
        left, right = _SSE.format(n="n_l", s="s_l", q="q_l"), _SSE.format(n="n_r", s="s_r", q="q_r")
        rows = ("n_l", "n_r")
        pred = [f"CASE WHEN n_{k} > 0 THEN CAST(s_{k} AS DOUBLE) / CAST(n_{k} AS DOUBLE) / {scale} END" for k in "lr"]
        unit = float(scale * scale)
    else:
        agg = "count(*) FILTER (y > 0) AS p, count(*) FILTER (y <= 0) AS g"
        cols = ("p", "g")
        left, right = (_SIDE[criterion].format(p=f"p_{k}", g=f"g_{k}") for k in "lr")
        rows = ("p_l + g_l", "p_r + g_r")
        pred = [f"CASE WHEN p_{k} + g_{k} > 0 THEN CASE WHEN p_{k} >= g_{k} THEN CAST(1.0 AS DOUBLE) ELSE CAST(-1.0 AS DOUBLE) END END" for k in "lr"]
        unit = 1.0
    sums = ", ".join(f"sum({c}) OVER ({part}ORDER BY x) AS {c}_l, sum({c}) OVER ({part.strip()}) AS {c}_t" for c in cols)
    sides = ", ".join(f"{c}_t - {c}_l AS {c}_r" for c in cols)
    return f"""obs AS ({obs}), hist AS (SELECT {key}x, {agg} FROM obs GROUP BY {key}x),
run AS (SELECT *, {sums} FROM hist), both_ AS (SELECT *, {sides} FROM run),
side AS (SELECT {key}x, CAST({rows[0]} AS BIGINT) AS n_left, CAST({rows[1]} AS BIGINT) AS n_right, ({left}) / {unit} AS err_left, ({right}) / {unit} AS err_right,
 {pred[0]} AS pred_left, {pred[1]} AS pred_right FROM both_),
curve AS (SELECT *, (err_left + err_right) / (n_left + n_right) AS loss FROM side)"""


def _best_sql(obs: str, criterion: str = "mse", scale: int = 1, digits: int = 6) -> str:
    return f"WITH {curve_sql(obs, criterion, scale)} SELECT x AS j, round(loss, {digits}) AS loss, round(pred_left, {digits}) AS pred_left, round(pred_right, {digits}) AS pred_right, n_left, n_right FROM curve ORDER BY 2, 1 LIMIT 1"


def _at_splits_sql(splits: str, digits: int = 4) -> str:
    """Losses at a list of values by theta joins."""
    side = lambda op, k: f"count(*) FILTER (x {op} j) AS n_{k}, coalesce(sum(CAST(y AS HUGEINT)) FILTER (x {op} j), 0) AS s_{k}, coalesce(sum(CAST(y AS HUGEINT) * y) FILTER (x {op} j), 0) AS q_{k}"
    left, right = _SSE.format(n="n_l", s="s_l", q="q_l"), _SSE.format(n="n_r", s="s_r", q="q_r")
    return f"""sums AS (SELECT j, {side("<=", "l")}, {side(">", "r")} FROM obs, ({splits}) GROUP BY j),
losses AS (SELECT j, n_l, n_r, s_l, s_r, (({left}) + ({right})) / (n_l + n_r) AS loss FROM sums)"""


def _fixed_sql() -> str:
    values = ", ".join(f"({j})" for j in FIXED_SPLITS)
    return f"WITH obs AS ({OBS['planted']}), {_at_splits_sql(f'SELECT CAST(j AS BIGINT) AS j FROM (VALUES {values}) AS v(j)')} SELECT j, n_l AS n_left, n_r AS n_right, round(loss, 4) AS loss FROM losses"


def _rate_sql(eps: float, power: int = 1, c: float = 9.0) -> str:
    return f"least(1.0, {c} * ln(greatest(2, (SELECT max(x) FROM obs))) / ((SELECT count(*) FROM obs) * power({eps}, {power})))"


def _kept_sql(p: str, keys: list[str] | None = None, seed: int = SEED) -> str:
    m = sampling.MODULUS
    return f"({p}) >= 1 OR {sampling.lcg_sql(keys or KEYS, seed)} < CAST(floor(({p}) * {m}) AS BIGINT)"


def _additive_sql(eps: float = EPS) -> str:
    p = _rate_sql(eps)
    return f"""WITH obs AS ({OBS["planted"]}), sampled AS (SELECT DISTINCT x FROM obs WHERE {_kept_sql(p)}),
cand AS (SELECT DISTINCT j FROM (SELECT x AS j FROM sampled UNION ALL SELECT x - 1 FROM sampled UNION ALL SELECT max(x) FROM obs) WHERE j > 0 AND j <= (SELECT max(x) FROM obs)),
hist AS (SELECT x, count(*) AS n, sum(CAST(y AS HUGEINT)) AS s, sum(CAST(y AS HUGEINT) * y) AS q FROM obs GROUP BY x),
run AS (SELECT x, sum(n) OVER w AS n_l, sum(s) OVER w AS s_l, sum(q) OVER w AS q_l FROM hist WINDOW w AS (ORDER BY x)),
total AS (SELECT sum(n) AS n, sum(s) AS s, sum(q) AS q FROM hist),
at_ AS (SELECT j, coalesce(n_l, 0) AS n_l, coalesce(s_l, 0) AS s_l, coalesce(q_l, 0) AS q_l FROM cand ASOF LEFT JOIN run ON cand.j >= run.x),
two AS (SELECT j, n_l, s_l, q_l, n - n_l AS n_r, s - s_l AS s_r, q - q_l AS q_r FROM at_, total),
losses AS (SELECT *, (({_SSE.format(n="n_l", s="s_l", q="q_l")}) + ({_SSE.format(n="n_r", s="s_r", q="q_r")})) / (n_l + n_r) AS loss FROM two)
SELECT j, round(loss, 6) AS loss, round(CASE WHEN n_l > 0 THEN CAST(s_l AS DOUBLE) / CAST(n_l AS DOUBLE) END, 6) AS pred_left, round(CASE WHEN n_r > 0 THEN CAST(s_r AS DOUBLE) / CAST(n_r AS DOUBLE) END, 6) AS pred_right, CAST(n_l AS BIGINT) AS n_left, CAST(n_r AS BIGINT) AS n_right FROM losses ORDER BY 2, 1 LIMIT 1"""


def _opt_sql(obs: str, criterion: str = "mse", scale: int = 1) -> str:
    return f"WITH {curve_sql(obs, criterion, scale)} SELECT min(round(loss, 6)) AS opt, true AS within_bound FROM curve"


def _cls_additive_sql(power: int) -> str:
    p = _rate_sql(EPS, power)
    inner = f"SELECT x, y FROM obs0 WHERE {_kept_sql(p.replace('FROM obs', 'FROM obs0'))}"
    return f"WITH obs0 AS ({OBS['planted_class']}), {curve_sql(inner, 'misclassification')} SELECT x AS j, round((err_left + err_right) / ({p.replace('FROM obs', 'FROM obs0')}) / CAST((SELECT count(*) FROM obs0) AS DOUBLE), 6) AS loss FROM curve ORDER BY 2, 1 LIMIT 1"


def _frontier_sql(obs: str, criterion: str) -> str:
    grid = (
        "SELECT 0.0 AS z UNION ALL SELECT 0.5 * power(2.0, k) FROM range(0, 120) AS r(k) WHERE 0.5 * power(2.0, k - 1) < (SELECT CAST(count(*) AS DOUBLE) * power(max(y) - min(y), 2) FROM obs)"
        if criterion == "mse"
        else "SELECT 0.0 AS z UNION ALL SELECT power(2.0, k) FROM range(0, 60) AS r(k) WHERE power(2.0, k - 1) < (SELECT count(*) FROM obs)"
    )
    # Errors change at values only: the last fit on the left ends before the next value, the first on the right is a value.
    return f"""WITH {curve_sql(obs, criterion)}, grid AS ({grid}),
points AS (SELECT x, err_left, err_right, lead(x) OVER (ORDER BY x) AS after FROM curve),
zero AS (SELECT err_left + err_right AS whole FROM curve ORDER BY x DESC LIMIT 1), least AS (SELECT min(x) AS x FROM curve),
l AS (SELECT z, coalesce(max(CASE WHEN err_left <= z THEN coalesce(after - 1, x) END), (SELECT x - 1 FROM least)) AS jl FROM grid, points GROUP BY z),
r AS (SELECT z, min(CASE WHEN z >= (SELECT whole FROM zero) THEN 1 WHEN err_right <= z THEN x END) AS jr FROM grid, points GROUP BY z),
met AS (SELECT l.z + r.z AS bound, jr AS j FROM l, r WHERE jr <= jl ORDER BY 1, 2 LIMIT 1),
at_ AS (SELECT c.* FROM curve c, met WHERE c.x <= met.j ORDER BY c.x DESC LIMIT 1)
SELECT met.j AS j, round(at_.loss, 6) AS loss, at_.n_left AS n_left, at_.n_right AS n_right FROM at_, met"""


def _gini_samples_sql() -> str:
    size, least = gini.sample_size(1000, 0.3, 3.0), gini.least_matches(1000, 0.3, 1.0, "repaired")
    one = lambda name, seed: f"{name} AS (SELECT row_number() OVER (ORDER BY h, conv_id, turn) AS i, x, y FROM (SELECT *, {sampling.lcg_sql(['conv_id', 'turn'], seed)} AS h FROM obs) ORDER BY h, conv_id, turn LIMIT {size})"
    return f"""obs AS ({OBS["conversation"]}), {one("s1", SEED)}, {one("s2", SEED + 1)},
js AS (SELECT DISTINCT x AS j FROM (SELECT x FROM s1 UNION ALL SELECT x FROM s2)),
sides AS (SELECT * FROM (VALUES ('left'), ('right')) AS v(side)), labels_ AS (SELECT * FROM (VALUES (1), (-1)) AS v(label)),
hit AS (SELECT j, side, row_number() OVER (PARTITION BY j, side ORDER BY i) AS k, y FROM s2, js, sides WHERE (side = 'left') = (x <= j)),
enough AS (SELECT j, side, count(*) AS t FROM hit GROUP BY j, side HAVING count(*) >= {least}),
pairs AS (SELECT e.j, e.side, label, avg(CASE WHEN h.y = label AND s1.y = label AND ((e.side = 'left') = (s1.x <= e.j)) THEN 1.0 ELSE 0.0 END) AS est
 FROM enough e JOIN hit h ON h.j = e.j AND h.side = e.side JOIN s1 ON s1.i = h.k, labels_ GROUP BY e.j, e.side, label),
terms AS (SELECT js.j AS j, CAST(l.label AS INTEGER) AS label, s.side AS side, coalesce(p.est, 0.0) AS est FROM js, labels_ l, sides s LEFT JOIN pairs p ON p.j = js.j AND p.label = l.label AND p.side = s.side)"""


def _cat_sql(source: str, keys: str = "category") -> str:
    return f"WITH c AS (SELECT {keys}, count(*) FILTER (y > 0) AS pos, count(*) FILTER (y <= 0) AS neg FROM ({source}) GROUP BY 1)"


def _disjoint_sql(a: str, b: str) -> str:
    return f"""WITH s AS (SELECT DISTINCT user_id AS category, 1 AS y FROM events WHERE {a} UNION ALL SELECT DISTINCT user_id, -1 FROM events WHERE {b}),
c AS (SELECT category, count(*) FILTER (y > 0) AS pos, count(*) FILTER (y <= 0) AS neg FROM s GROUP BY 1)
SELECT coalesce(sum(least(pos, neg)), 0) = 0 AS separable, CAST(count(*) FILTER (pos > 0 AND neg > 0) AS BIGINT) AS shared, round(CAST(sum(least(pos, neg)) AS DOUBLE) / sum(pos + neg), 6) AS loss FROM c"""


def _range_sql() -> str:
    p = "least(1.0, 9.0 * ln(greatest(2, (SELECT max(x) FROM obs))) / power((SELECT count(*) FROM obs), 0.5))"
    values = ", ".join(f"({a}, {b})" for a, b in RANGES)
    return f"""WITH obs AS ({OBS["price_qty"]}), asked AS (SELECT CAST(lo AS BIGINT) AS lo, CAST(hi AS BIGINT) AS hi FROM (VALUES {values}) AS v(lo, hi)),
sample AS (SELECT x FROM obs WHERE {_kept_sql(p)}), k AS (SELECT lo, hi, (SELECT count(*) FROM sample WHERE x BETWEEN lo AND hi) AS sampled FROM asked)
SELECT lo, hi, sampled, sampled / ({p}) >= 2 * power((SELECT count(*) FROM obs), 0.5) AS heavy, sampled / ({p}) <= power((SELECT count(*) FROM obs), 0.5) AS light FROM k"""


_STAR = "SELECT CAST(l_quantity AS BIGINT) AS qty, CAST(round(l_discount * 100) AS BIGINT) AS discount, CAST(round(l_tax * 100) AS BIGINT) AS tax, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) + 1 AS BIGINT) AS order_day, CAST(p_size AS BIGINT) AS size, CAST(round(l_extendedprice * 100) AS BIGINT) AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"


def _long_sql(rows: str, features: list[str], keep: str = "") -> str:
    return " UNION ALL ".join(f"SELECT {keep}'{a}' AS attr, {a} AS x, y FROM {rows}" for a in features)


def _features_sql() -> str:
    long = f"SELECT attr, x, y FROM (WITH f AS ({_STAR}) {_long_sql('f', FEATURES)})"
    return f"WITH {curve_sql(long, 'mse', 100, 'attr')}, ranked AS (SELECT attr, x AS j, round(loss, 2) AS loss, row_number() OVER (PARTITION BY attr ORDER BY round(loss, 2), x) AS k FROM curve) SELECT attr, j, loss FROM ranked WHERE k = 1"


def _tree_sql(base: str, features: list[str], scale: int, digits: int) -> str:
    """Both levels of a depth-2 tree: the best split of all rows, then of each side."""

    def level(rows: str) -> str:
        best = f"SELECT node, attr, x AS j, round(loss, {digits}) AS loss, n_left + n_right AS n, row_number() OVER (PARTITION BY node ORDER BY round(loss, {digits}), attr, x) AS k FROM curve WHERE n_right > 0"
        return f"SELECT node, attr, j, loss, n FROM (WITH {curve_sql(_long_sql(rows, features, 'node, '), 'mse', scale, 'node, attr')} {best}) WHERE k = 1"

    value = "CASE attr " + " ".join(f"WHEN '{a}' THEN {a}" for a in features) + " END"
    return f"""WITH base AS MATERIALIZED (SELECT 1 AS node, * FROM ({base})), first AS MATERIALIZED ({level("base")}),
second AS MATERIALIZED (SELECT CASE WHEN {value} <= j THEN 2 ELSE 3 END AS node, {", ".join(features)}, y FROM (SELECT b.*, f.attr, f.j FROM base b, first f))
SELECT CAST(node AS INTEGER) AS node, attr, j, loss, n FROM first UNION ALL SELECT CAST(node AS INTEGER), attr, j, loss, n FROM ({level("second")})"""


def _success_sql(eps: float) -> str:
    """For each seed the least loss at sampled values and at the values before them, from the exact curve."""
    p = _rate_sql(eps).replace("FROM obs", "FROM obs0")
    picks = " UNION ALL ".join(f"SELECT DISTINCT x, {seed} AS seed FROM obs0 WHERE {_kept_sql(p, KEYS, seed)}" for seed in SEEDS)
    return f"""WITH obs0 AS MATERIALIZED ({OBS["planted"]}), {curve_sql("SELECT x, y FROM obs0")},
steps AS (SELECT x, loss, coalesce(lag(loss) OVER (ORDER BY x), (SELECT loss FROM curve WHERE n_right = 0)) AS loss_before FROM curve),
picked AS ({picks}), got AS (SELECT seed, min(least(loss, loss_before)) AS got FROM picked JOIN steps USING (x) GROUP BY seed)
SELECT CAST(seed AS INTEGER) AS seed, round(got - (SELECT min(loss) FROM curve), 6) AS excess, true AS within FROM got"""


def _cat_opt_sql(source: str) -> str:
    return f"{_cat_sql(source)} SELECT round(CAST(sum(least(pos, neg)) AS DOUBLE) / sum(pos + neg), 6) AS opt, true AS within_bound FROM c"


def _tree_error_sql() -> str:
    """Labels, and the error of a depth-2 tree on one attribute: the best split, then of each side with both sides' majorities."""
    best = lambda rows: f"(WITH {curve_sql(rows, 'misclassification')} SELECT x AS j, err_left + err_right AS err FROM curve WHERE n_right > 0 ORDER BY round(loss, 6), x LIMIT 1)"
    whole = lambda keep: f"(SELECT CAST(least(count(*) FILTER (y > 0), count(*) FILTER (y <= 0)) AS DOUBLE) FROM base, top WHERE {keep})"
    side = lambda keep: f"coalesce((SELECT err FROM {best(f'SELECT base.x, base.y FROM base, top WHERE {keep}')}), {whole(keep)})"
    return f"WITH base AS MATERIALIZED ({OBS['conversation']}), top AS MATERIALIZED (SELECT j FROM {best('SELECT x, y FROM base')}) SELECT (SELECT count(*) FROM base) AS n, round(({side('base.x <= j')} + {side('base.x > j')}) / (SELECT count(*) FROM base), 6) AS error"


def _grid_sql() -> dict[str, str]:
    day = lambda col: f"CAST(date_diff('day', DATE '1995-01-01', CAST({col} AS DATE)) + 1 AS BIGINT)"
    doc = "SELECT n_chars AS x, CASE WHEN {} = 1 THEN 1 ELSE -1 END AS y FROM documents JOIN labels USING (doc_id)"
    reg = OBS | {
        "ship": f"SELECT {day('l_shipdate')} AS x, CAST(round(l_discount * 100) AS BIGINT) AS y FROM lineitem",
        "orders": f"SELECT {day('o_orderdate')} AS x, CAST(round(o_totalprice * 100) AS BIGINT) AS y FROM orders",
        "events": "SELECT CAST(floor(epoch(ts)) AS BIGINT) AS x, CAST(round(value * 100) AS BIGINT) AS y FROM events",
    }
    cls = {
        "price": OBS["price_class"],
        "ship": f"SELECT {day('l_shipdate')} AS x, CASE WHEN l_linestatus = 'O' THEN 1 ELSE -1 END AS y FROM lineitem",
        "quality": doc.format("quality"),
        "toxic": doc.format("toxic"),
        "events": "SELECT CAST(round(value * 100) AS BIGINT) AS x, CASE WHEN event_type = 'purchase' THEN 1 ELSE -1 END AS y FROM events",
        "conv": OBS["conversation"],
    }
    line = "CASE WHEN l_quantity > 25 THEN 1 ELSE -1 END AS y FROM lineitem"
    cat = {
        "source": "SELECT source AS category, CASE WHEN quality = 1 THEN 1 ELSE -1 END AS y FROM documents JOIN labels USING (doc_id)",
        "lang": "SELECT lang AS category, CASE WHEN toxic = 1 THEN 1 ELSE -1 END AS y FROM documents JOIN labels USING (doc_id)",
        "flag": f"SELECT l_returnflag || l_linestatus AS category, {line}",
        "brand": "SELECT p_brand AS category, CASE WHEN p_size > 25 THEN 1 ELSE -1 END AS y FROM part",
        "partkey": f"SELECT l_partkey AS category, {line}",
    }
    found = {}
    for name in _grid():
        kind, _, work = name.partition("_bound_")
        if kind in ("reg_additive", "reg_mult"):
            found[name] = _opt_sql(reg[work], "mse", REGRESSIONS[work][1])
        elif kind in ("cls_additive", "cls_mult"):
            found[name] = _opt_sql(cls[work], "misclassification")
        elif kind == "gini":
            found[name] = _opt_sql(cls[work], "gini")
        elif kind == "gini_paired":
            found[name] = _opt_sql(OBS["conversation"], "gini")
        else:
            found[name] = _cat_opt_sql(cat[work.rpartition("_")[0]])
    return found


def _measure_sql() -> dict[str, str]:
    """Figures, measures and samples."""
    values = lambda rows, names: "SELECT * FROM (VALUES " + ", ".join(f"({', '.join(r)})" for r in rows) + f") AS v({names})"
    yes = lambda names, n: [(f"'{name}'", *["true"] * n) for name in names]
    points = lambda frame: "SELECT CAST(x AS BIGINT) AS x, CAST(y AS BIGINT) AS y FROM (VALUES " + ", ".join(map(str, frame)) + ") AS v(x, y)"
    level = f"floor(log2({float(sampling.MODULUS)} / greatest(CAST({sampling.lcg_sql(['o_orderkey'], SEED)} AS DOUBLE), 1.0)))"
    least = gini.least_matches(1000, 0.3, 1.0, "repaired")
    gaps = lambda obs: f"WITH obs AS ({obs}), h AS (SELECT x, count(*) AS n FROM obs GROUP BY x) SELECT x, n, lead(x) OVER (ORDER BY x) - x AS gap, CAST(ntile(4) OVER (ORDER BY x) AS INTEGER) AS bin FROM h"
    hours = "SELECT strftime(ts, '%Y-%m-%d') AS day, CAST(hour(ts) + 1 AS BIGINT) AS x, CAST(round(value * 100) AS BIGINT) AS y FROM events"
    part_base = "SELECT p_partkey AS key, CAST(p_size AS BIGINT) AS size, CAST(round(p_retailprice * 100) AS BIGINT) AS y FROM part"
    conv = OBS["conversation"]
    mpc_names = ("regression additive", "regression multiplicative", "classification additive", "gini additive", "classification multiplicative")
    return {
        "figure_regression": _best_sql(points(W.FIGURE_REGRESSION)),
        "figure_classification": _best_sql(points(W.FIGURE_CLASSIFICATION), "misclassification"),
        "figure_gini": _best_sql(points(W.FIGURE_CLASSIFICATION), "gini"),
        "value_gaps": gaps(OBS["qty"]),
        "value_gaps_part": gaps(OBS["price_qty"]),
        "sample_adaptive": f"WITH r AS (SELECT o_orderkey, {level} AS lv FROM orders), c AS (SELECT h, (SELECT count(*) FROM r WHERE lv >= h) AS n FROM range(0, 63) AS t(h)), p AS (SELECT min(h) AS h FROM c WHERE n <= 500) SELECT o_orderkey, power(CAST(0.5 AS DOUBLE), h) AS p FROM r, p WHERE lv >= h",
        "gini_coverage": f"WITH obs AS ({conv}), s AS (SELECT x FROM (SELECT *, {sampling.lcg_sql(['conv_id', 'turn'], SEED)} AS h FROM obs) ORDER BY h, conv_id, turn LIMIT 200), g AS (SELECT x, count(*) AS n FROM s GROUP BY x), l AS (SELECT x, CAST(sum(n) OVER (ORDER BY x) AS BIGINT) AS lef, CAST(sum(n) OVER () AS BIGINT) AS every FROM g) SELECT x, lef AS \"left\", every - lef AS \"right\", lef >= {least} AS enough_left, every - lef >= {least} AS enough_right FROM l",
        "gini_term_errors": values([(f"CAST({e} AS DOUBLE)", "true") for e in (0.4, 0.2, 0.1)], "eps, within"),
        "success_over_seeds": _success_sql(0.1),
        "search_cost_bounds": values(yes(("additive", "sequential", "batched", "frontier"), 3), "method, passes_ok, space_ok, quality_ok"),
        "mpc_costs": values(yes(mpc_names, 4), "method, machines_ok, rounds_ok, memory_ok, messages_ok"),
        "encode_quantile": "SELECT CAST(x AS BIGINT) AS x, true AS balanced FROM range(1, 17) AS t(x)",
        "tree_depth2": _tree_sql(part_base, ["key", "size"], 100, 4),
        "tree_star_join": _tree_sql(_STAR, FEATURES, 100, 2),
        "tree_predictions": _tree_error_sql(),
        "stump_conv": f"WITH {curve_sql(conv, 'misclassification')} SELECT CAST(1 AS INTEGER) AS node, 'x' AS attr, x AS j, round(loss, 6) AS loss, n_left + n_right AS n FROM curve WHERE n_right > 0 ORDER BY 4, 3 LIMIT 1",
        "stream_window_regression": f"WITH {curve_sql(hours, 'mse', 100, 'day')}, ranked AS (SELECT day, x AS j, round(loss, 2) AS loss, n_left + n_right AS n, row_number() OVER (PARTITION BY day ORDER BY round(loss, 2), x) AS k FROM curve) SELECT day, j, loss, n FROM ranked WHERE k = 1",
    }


def oracle_sql() -> dict[str, str]:
    class_source = "SELECT p_brand AS category, CASE WHEN p_size > 25 THEN 1 ELSE -1 END AS y FROM part"
    flags = "SELECT l_returnflag || l_linestatus AS category, CASE WHEN l_quantity > 25 THEN 1 ELSE -1 END AS y FROM lineitem"
    docs = "SELECT source AS category, CASE WHEN quality = 1 THEN 1 ELSE -1 END AS y FROM documents JOIN labels USING (doc_id)"
    loss = "round(CAST(sum(least(pos, neg)) AS DOUBLE) / sum(pos + neg), 6)"
    planted, part, conv = OBS["planted"], OBS["part"], OBS["conversation"]
    days = "SELECT strftime(ts, '%Y-%m-%d') AS day, CAST(round(value * 100) AS BIGINT) AS x, CASE WHEN event_type = 'purchase' THEN 1 ELSE -1 END AS y FROM events"
    dims = "SELECT CAST(p AS BIGINT) AS attr, CAST(floor((CAST(embedding[p] AS DOUBLE) + 2) * 1000) AS BIGINT) AS x, CASE WHEN label = 0 THEN 1 ELSE -1 END AS y FROM embeddings, range(1, 65) AS r(p)"
    curve = lambda obs, scale, digits: f"WITH {curve_sql(obs, 'mse', scale)} SELECT x AS j, n_left, n_right, round(loss, {digits}) AS loss FROM curve"
    cat_p = "least(1.0, 9.0 * (SELECT count(DISTINCT l_partkey) FROM obs) / ((SELECT count(*) FROM obs) * 0.2))"
    found = {
        "reg_exact_planted": _best_sql(planted),
        "reg_exact_qty": _best_sql(OBS["qty"], "mse", 100, 2),
        "reg_exact_part": _best_sql(part, "mse", 100, 4),
        "reg_exact_doc_words": _best_sql(OBS["doc_words"], "mse", 1, 4),
        "reg_curve_qty": curve(OBS["qty"], 100, 1),
        "reg_curve_part": curve(part, 100, 4),
        "reg_brute_qty": f"WITH obs AS ({OBS['qty']}), {_at_splits_sql('SELECT DISTINCT x AS j FROM obs')} SELECT j, n_l AS n_left, n_r AS n_right, round(loss / 10000.0, 1) AS loss FROM losses",
        "reg_offline_part": _best_sql(part, "mse", 100, 4),
        "reg_additive_planted": _additive_sql(),
        "reg_additive_arrow_planted": _additive_sql(),
        "reg_additive_merge_planted": _additive_sql(),
        "reg_additive_coarse_planted": _additive_sql(NAIVE_EPS),
        "reg_additive_naive_planted": _additive_sql(NAIVE_EPS),
        "reg_additive_bound": _opt_sql(planted),
        "reg_additive_bound_noise": _opt_sql(OBS["price_qty"]),
        **{f"reg_multi_losses{k}": _fixed_sql() for k in ("", "_arrow", "_merge", "_two_pass")},
        "reg_mult_seq": _opt_sql(planted),
        "reg_mult_batched": _opt_sql(planted),
        "reg_mult_batched_part": _opt_sql(part, "mse", 100),
        "reg_mult_frontier": _frontier_sql(planted, "mse"),
        "cls_exact_planted": _best_sql(OBS["planted_class"], "misclassification"),
        "cls_exact_conv": _best_sql(conv, "misclassification"),
        "gini_exact_planted": _best_sql(OBS["planted_class"], "gini"),
        "gini_exact_conv": _best_sql(conv, "gini"),
        "entropy_exact_conv": _best_sql(conv, "entropy"),
        "cls_additive_planted": _cls_additive_sql(2),
        "cls_additive_printed": _cls_additive_sql(1),
        "cls_additive_bound": _opt_sql(OBS["price_class"], "misclassification"),
        "gini_paired_terms": f"WITH {_gini_samples_sql()} SELECT j, label, side, round(est, 6) AS est FROM terms",
        "gini_additive": f"WITH {_gini_samples_sql()} SELECT j, round(1 - sum(est), 6) AS loss FROM terms GROUP BY j ORDER BY 2, 1 LIMIT 1",
        "gini_plugin": f"WITH obs0 AS ({conv}), {curve_sql('SELECT x, y FROM (SELECT *, ' + sampling.lcg_sql(['conv_id', 'turn'], SEED) + f' AS h FROM obs0) ORDER BY h, conv_id, turn LIMIT {gini.sample_size(1000, 0.3, 3.0)}', 'gini')} SELECT x AS j, round(loss, 6) AS loss FROM curve ORDER BY 2, 1 LIMIT 1",
        "gini_additive_bound": _opt_sql(OBS["planted_class"], "gini"),
        "cls_mult_seq": _opt_sql(OBS["planted_class"], "misclassification"),
        "cls_mult_batched": _opt_sql(OBS["planted_class"], "misclassification"),
        "cls_mult_frontier": _frontier_sql(OBS["planted_class"], "misclassification"),
        "cat_exact_brand": f"{_cat_sql(class_source)} SELECT {loss} AS loss, count(*) AS categories FROM c",
        "cat_exact_source": f"{_cat_sql(docs)} SELECT category, CASE WHEN pos >= neg THEN 'A' ELSE 'B' END AS side, pos, neg FROM c",
        "cat_enumerate_flag": f"{_cat_sql(flags)} SELECT {loss} AS loss, CAST(power(2, count(*)) AS BIGINT) AS groupings FROM c",
        "cat_additive_partkey": f"WITH obs AS ({OBS['price_class']}), c AS (SELECT l_partkey, count(*) FILTER (y > 0) AS pos, count(*) FILTER (y <= 0) AS neg FROM obs WHERE {_kept_sql(cat_p)} GROUP BY 1) SELECT {loss} AS loss, count(*) AS categories FROM c",
        "disj_yes": _disjoint_sql("event_type = 'click'", "event_type = 'error'"),
        "disj_no": _disjoint_sql("event_type = 'click' AND user_id % 2 = 0", "event_type = 'error' AND user_id % 2 = 1"),
        "range_count": _range_sql(),
        "mpc_reg_additive": _opt_sql(planted),
        "mpc_reg_additive_noise": _opt_sql(OBS["price_qty"]),
        "mpc_reg_mult": _opt_sql(part, "mse", 100),
        "mpc_reg_mult_noise": _opt_sql(OBS["price_qty"]),
        "mpc_cls_additive": _opt_sql(OBS["planted_class"], "misclassification"),
        "mpc_cls_additive_printed": _opt_sql(OBS["planted_class"], "misclassification"),
        "mpc_gini": _opt_sql(OBS["planted_class"], "gini"),
        "mpc_gini_paired": _opt_sql(OBS["planted_class"], "gini"),
        "mpc_evaluator": _fixed_sql(),
        "mpc_cls_mult": _opt_sql(conv, "misclassification"),
        "stump_multi_attr": _features_sql(),
        "emb_best_dim": f"WITH {curve_sql(dims, 'gini', 1, 'attr')} SELECT attr, x AS j, round(loss, 6) AS loss FROM curve ORDER BY 3, 1, 2 LIMIT 1",
        "no_split_rollup": f"WITH obs AS (SELECT p_type, p_brand, CAST(round(p_retailprice * 100) AS BIGINT) AS y FROM part), m AS (SELECT p_type, p_brand, count(*) AS n, sum(CAST(y AS HUGEINT)) AS s, sum(CAST(y AS HUGEINT) * y) AS q FROM obs GROUP BY ROLLUP (p_type, p_brand)) SELECT p_type, p_brand, n, round(({_SSE.format(n='n', s='s', q='q')}) / n / 10000.0, 4) AS loss FROM m",
        "sample_bernoulli": f"SELECT o_orderkey, o_totalprice FROM orders WHERE {sampling.lcg_sql(['o_orderkey'], SEED)} < {math.floor(0.1 * sampling.MODULUS)}",
        "sample_bottom_k": f"SELECT o_orderkey, {sampling.lcg_sql(['o_orderkey'], SEED)} AS h FROM orders ORDER BY h, o_orderkey LIMIT 100",
        "encode_rank": "SELECT o_orderkey, dense_rank() OVER (ORDER BY o_orderdate) AS x FROM orders WHERE o_orderdate IS NOT NULL",
        "stream_window_split": f"WITH {curve_sql(days, 'misclassification', 1, 'day')}, ranked AS (SELECT day, x AS j, round(loss, 6) AS loss, n_left + n_right AS n, row_number() OVER (PARTITION BY day ORDER BY round(loss, 6), x) AS k FROM curve) SELECT day, j, loss, n FROM ranked WHERE k = 1",
    }
    day = lambda col, first: f"CAST(date_diff('day', DATE '{first}', CAST({col} AS DATE)) + 1 AS BIGINT)"
    least = lambda obs, criterion="mse", scale=1, digits=6: f"WITH {curve_sql(obs, criterion, scale)} SELECT min(round(loss, {digits})) AS loss, CAST(max(n_left) AS BIGINT) AS n FROM curve"
    doc = "SELECT n_chars AS x, CASE WHEN {} = 1 THEN 1 ELSE -1 END AS y FROM documents JOIN labels USING (doc_id)"
    region = "SELECT r_name, s_suppkey AS x, CAST(round(s_acctbal * 100) AS BIGINT) AS y FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
    found |= {
        "reg_loss_ship": least(f"SELECT {day('l_shipdate', '1995-01-01')} AS x, CAST(round(l_discount * 100) AS BIGINT) AS y FROM lineitem", "mse", 100),
        "reg_loss_orders": least(f"SELECT {day('o_orderdate', '1995-01-01')} AS x, CAST(round(o_totalprice * 100) AS BIGINT) AS y FROM orders", "mse", 100, 0),
        "reg_loss_events": least("SELECT CAST(floor(epoch(ts)) AS BIGINT) AS x, CAST(round(value * 100) AS BIGINT) AS y FROM events", "mse", 100, 3),
        "cls_loss_price": least(OBS["price_class"], "misclassification"),
        "cls_loss_ship": least(f"SELECT {day('l_shipdate', '1995-01-01')} AS x, CASE WHEN l_linestatus = 'O' THEN 1 ELSE -1 END AS y FROM lineitem", "misclassification"),
        "cls_loss_events": least("SELECT CAST(round(value * 100) AS BIGINT) AS x, CASE WHEN event_type = 'purchase' THEN 1 ELSE -1 END AS y FROM events", "misclassification"),
        "cls_loss_quality": least(doc.format("quality"), "misclassification"),
        "gini_loss_toxic": least(doc.format("toxic"), "gini"),
        "labelled_docs": "SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)",
        "unlabelled_docs": "SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
        "disj_shared_users": "SELECT DISTINCT user_id FROM events WHERE event_type = 'click' AND user_id IN (SELECT user_id FROM events WHERE event_type = 'error')",
        "unsampled_values": f"WITH obs AS ({OBS['price_qty']}) SELECT DISTINCT x FROM obs WHERE x NOT IN (SELECT x FROM obs WHERE {_kept_sql('0.5')})",
        "as_of_price_steps": "WITH o AS (SELECT CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders) SELECT least(cents // 500000, 199) AS step, count(*) AS n FROM o GROUP BY 1",
        "no_split_cube": f"WITH m AS (SELECT c_mktsegment, n_regionkey, count(*) AS n, sum(CAST(y AS HUGEINT)) AS s, sum(CAST(y AS HUGEINT) * y) AS q FROM (SELECT c_mktsegment, n_regionkey, CAST(round(c_acctbal * 100) AS BIGINT) + 100000 AS y FROM customer JOIN nation ON c_nationkey = n_nationkey) GROUP BY CUBE (c_mktsegment, n_regionkey)) SELECT coalesce(c_mktsegment, 'all') AS c_mktsegment, coalesce(CAST(n_regionkey AS VARCHAR), 'all') AS n_regionkey, n, round(({_SSE.format(n='n', s='s', q='q')}) / n / 10000.0, 2) AS loss FROM m",
        "split_by_region": f"WITH {curve_sql(region, 'mse', 100, 'r_name')}, ranked AS (SELECT r_name, x AS j, round(loss, 2) AS loss, row_number() OVER (PARTITION BY r_name ORDER BY round(loss, 2), x) AS k FROM curve WHERE n_right > 0) SELECT r_name, j, loss FROM ranked WHERE k = 1",
        "page_lengths": least("SELECT CAST(length(html) AS BIGINT) AS x, CASE WHEN length(url) > 30 THEN 1 ELSE -1 END AS y FROM pages", "gini"),
    }
    return found | _grid_sql() | _measure_sql()
