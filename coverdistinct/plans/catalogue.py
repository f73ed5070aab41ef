"""The query catalogue: each method, variant, baseline, measure, workload and operator on
the given tables, with its DuckDB SQL where SQL can replay it."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import sqlapi, theory
from ..functions.hashing import SPAN, hash60
from ..operators import counters, estimators, fused, planner, probe, sampling, spectrum
from ..sources import streams
from . import duck, workloads

#: A decimal literal is a double in Spark's plans; with an exponent it is one in DuckDB too.
_DECIMAL = re.compile(r"(?<![\w.'])(\d+\.\d+)(?![\w.'])")

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def tidy(df: DataFrame) -> DataFrame:
    """Doubles to six places, all integers as long: what the oracle gives."""
    out = []
    for f in df.schema.fields:
        c = F.col(f"`{f.name}`")
        if isinstance(f.dataType, (T.DoubleType, T.FloatType, T.DecimalType)):
            c = F.round(c.cast("double"), 6)
        elif isinstance(f.dataType, (T.IntegerType, T.ShortType, T.ByteType)):
            c = c.cast("long")
        out.append(c.alias(f.name))
    return df.select(*out)


def sql(query: str, doubles: str = "", longs: str = "") -> str:
    parts = [f"round(CAST({c} AS DOUBLE), 6) AS {c}" for c in doubles.split()] + [f"CAST({c} AS BIGINT) AS {c}" for c in longs.split()]
    return f"SELECT * REPLACE ({', '.join(parts)}) FROM ({query})" if parts else query


def query(name: str, oracle: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = lambda spark, sf_dir: tidy(f(spark, sf_dir))
        if oracle is not None:
            ORACLES[name] = _DECIMAL.sub(r"\1e0", oracle)
        return f
    return add


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def tagged(parts: dict[str, str], column: str = "stream") -> str:
    return " UNION ALL ".join(f"SELECT '{k}' AS {column}, * FROM ({v})" for k, v in parts.items())


def _tag(df: DataFrame, value: str, column: str = "stream") -> DataFrame:
    return df.select(F.lit(value).alias(column), "*")


load = streams.load
S = duck.stream
RATES = [0.1, 0.01]
LOW_SKEW = ["part_key", "ship_date", "cust_key"]
EVERY = list(streams.STREAMS)

# --- samplers ---

@query("s1_bernoulli_count", " UNION ALL ".join(
    f"SELECT CAST({r!r} AS DOUBLE) AS rate, count(*) AS l, count(DISTINCT element) AS ns FROM ({duck.sample(S('part_key'), r)})" for r in (0.1, 0.01, 1.0)))
def _(spark, d):
    x = load(spark, d, "part_key")
    return union([sampling.bernoulli(x, r).agg(F.count(F.lit(1)).alias("l"), F.count_distinct("element").alias("ns")).select(F.lit(r).alias("rate"), "l", "ns") for r in (0.1, 0.01, 1.0)])


@query("s2_native_sample")
def _(spark, d):
    return sampling.native(load(spark, d, "part_key"), 0.1).agg(F.count(F.lit(1)).alias("l"), F.count_distinct("element").alias("ns"))


@query("s3_fixed_size", f"SELECT count(*) AS l, count(DISTINCT element) AS ns, max(h) AS top FROM (SELECT element, {duck.h60(chr(39).join(['occ || ', '|s42', '']))} AS h FROM ({S('cust_key')}) ORDER BY h, occ LIMIT 1000)")
def _(spark, d):
    y = sampling.fixed_size(load(spark, d, "cust_key"), 1000)
    return y.agg(F.count(F.lit(1)).alias("l"), F.count_distinct("element").alias("ns"), F.max(hash60(F.col("occ"), "s", 42)).alias("top"))


PRIORITY_RATES = {"1-URGENT": 0.5, "2-HIGH": 0.2, "3-MEDIUM": 0.1}


@query("s5_stratified", " UNION ALL ".join(
    f"SELECT priority, count(*) AS l, count(DISTINCT element) AS ns FROM ({duck.sample(S('cust_key', {'priority': 'o_orderpriority'}), r)}) WHERE priority = '{p}' GROUP BY ALL" for p, r in PRIORITY_RATES.items()))
def _(spark, d):
    y = sampling.by_group(load(spark, d, "cust_key", {"priority": "o_orderpriority"}), "priority", PRIORITY_RATES)
    return y.groupBy("priority").agg(F.count(F.lit(1)).alias("l"), F.count_distinct("element").alias("ns"))


@query("s6_with_replacement")
def _(spark, d):
    return sampling.with_replacement(load(spark, d, "part_key"), 0.1).agg(F.count(F.lit(1)).alias("l"), F.count_distinct("element").alias("ns"))


@query("s7_block_sample")
def _(spark, d):
    return streams.block_sample(spark, f"{d}/lineitem.parquet", 0.9).groupBy("design").agg(F.count(F.lit(1)).alias("l"), F.count_distinct("l_partkey").alias("ns"))


# --- counters ---

@query("c1_exact", tagged({s: f"SELECT count(DISTINCT element) AS n, count(*) AS length FROM ({S(s)})" for s in EVERY}))
def _(spark, d):
    return union([_tag(estimators.exact(load(spark, d, s)), s) for s in EVERY])


def _counter(name: str, c, oracle: Callable[[str], str] | None, names: list[str], rate: float = 1.0):
    @query(name, sql(tagged({s: oracle(duck.sample(S(s), rate)) for s in names}), "ns_hat") if oracle else None)
    def _(spark, d):
        return union([_tag(c.estimate(c.state(sampling.bernoulli(load(spark, d, s), rate))), s) for s in names])


_counter("c2_hll_m200", counters.HyperLogLog(200), lambda y: duck.hll(y, 200), ["part_key", "cust_key", "user", "flow"])
_counter("c2_hll_m10_smallrange", counters.HyperLogLog(10), lambda y: duck.hll(y, 10), ["event_type", "doc_source", "user"])
_counter("c3_builtin", counters.BuiltinHll(), None, ["part_key", "cust_key", "user"])
_counter("c4_sketch", counters.HllSketch(10), None, ["part_key", "cust_key", "user"])
_counter("c5_bottom_m", counters.BottomM(200), lambda y: duck.bottom_m(y, 200), ["part_key", "cust_key", "user"])
_counter("c7_max_term", counters.MaxTerm(200), None, ["part_key", "cust_key", "user"])
_counter("c8_linear", counters.Linear(4096), lambda y: duck.linear(y, 4096), ["part_key", "cust_key", "user"])


@query("c7_max_term_histogram", f"SELECT CAST(rank AS BIGINT) AS rank, count(*) AS registers FROM ({duck.registers(S('part_key'), 200)}) GROUP BY ALL")
def _(spark, d):
    c = counters.MaxTerm(200)
    return c.histogram(c.state(load(spark, d, "part_key")))


@query("c2_registers", f"SELECT CAST(bucket AS BIGINT) AS bucket, CAST(rank AS BIGINT) AS rank FROM ({duck.registers(S('cust_key'), 200)})")
def _(spark, d):
    c = counters.HyperLogLog(200)
    return c.state(load(spark, d, "cust_key"))


@query("c6_theta_sets")
def _(spark, d):
    """Union, intersection and difference of two days' flows, from theta sketches."""
    x = load(spark, d, "flow", {"half": "case when day(ts) <= 15 then 'a' else 'b' end"})
    s = counters.Theta().state(x, ["half"])
    a, b = s.where("half = 'a'").select(F.col("sketch").alias("a")), s.where("half = 'b'").select(F.col("sketch").alias("b"))
    return a.crossJoin(b).select(
        F.theta_sketch_estimate(F.theta_union("a", "b")).alias("either"), F.theta_sketch_estimate(F.theta_intersection("a", "b")).alias("both"),
        F.theta_sketch_estimate(F.theta_difference("a", "b")).alias("first_only"))


EFFICIENCY_M, EFFICIENCY_RUNS = 50, 400
_VALUES = f"SELECT DISTINCT element FROM ({S('cust_key')})"
_SEEDED = f"SELECT run, {duck.h60(chr(39).join(['element || ', '|v', ' || run']))} AS h, {duck.h32(chr(39).join(['element || ', '|v', ' || run']))} % {EFFICIENCY_M} AS b, {duck.rank(chr(39).join(['element || ', '|v', ' || run']))} AS r FROM ({_VALUES}), range({EFFICIENCY_RUNS}) q(run)"


def _efficiency(spark, d) -> DataFrame:
    values = load(spark, d, "cust_key").select("element").distinct()
    runs = workloads.counter_runs(values, EFFICIENCY_M, EFFICIENCY_RUNS)
    n = values.agg(F.count(F.lit(1)).cast("double").alias("n"))
    out = runs.crossJoin(F.broadcast(n)).groupBy("procedure", "n").agg(F.var_pop("ns_hat").alias("v"), F.count(F.lit(1)).alias("runs"))
    return out.select("procedure", F.lit(EFFICIENCY_M).alias("m"), "runs", theory.efficiency(F.col("n"), F.lit(EFFICIENCY_M), F.col("v")).alias("efficiency"))


@query("c_efficiency", sql(
    f"WITH s AS MATERIALIZED ({_SEEDED}), n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM ({_VALUES})) "
    f"SELECT procedure, CAST({EFFICIENCY_M} AS BIGINT) AS m, count(*) AS runs, n * n / {EFFICIENCY_M} / var_pop(ns_hat) AS efficiency FROM ("
    f"SELECT 'bottom_m' AS procedure, run, {EFFICIENCY_M - 1} / (CAST(max(h) AS DOUBLE) / {float(SPAN)}) AS ns_hat FROM (SELECT run, h, row_number() OVER (PARTITION BY run ORDER BY h) AS k FROM s) WHERE k <= {EFFICIENCY_M} GROUP BY run "
    f"UNION ALL SELECT 'hll', run, {duck.hll_formula(EFFICIENCY_M)} FROM (SELECT run, count(*) AS used, sum(pow(2.0, -r)) AS z FROM (SELECT run, b, max(r) AS r FROM s GROUP BY ALL) GROUP BY run)), n GROUP BY procedure, n", "efficiency"))
def _(spark, d):
    """Empirical relative efficiency over 400 seeds."""
    return _efficiency(spark, d).where("procedure <> 'max_term'")


@query("c_efficiency_max_term")
def _(spark, d):
    return _efficiency(spark, d).where("procedure = 'max_term'")


# --- spectra ---

SPEC = ["order_key", "word", "cust_key"]


@query("g1_spectrum", tagged({s: f"SELECT f AS i, count(*) AS e_i FROM ({duck.counts(duck.sample(S(s), 0.1))}) GROUP BY ALL" for s in SPEC}))
def _(spark, d):
    return union([_tag(spectrum.spectrum(sampling.bernoulli(load(spark, d, s), 0.1)), s) for s in SPEC])


@query("g2_heads", tagged({s: duck.heads(duck.sample(S(s), 0.1)) for s in SPEC}))
def _(spark, d):
    return union([_tag(spectrum.heads(sampling.bernoulli(load(spark, d, s), 0.1)), s) for s in SPEC])


@query("g3_good_turing", sql(tagged({s: f"SELECT f - 1 AS i, count(*) AS e_next, f * count(*) / sum(f * count(*)) OVER () AS p_i FROM ({duck.counts(duck.sample(S(s), 0.1))}) GROUP BY f" for s in SPEC}), "p_i", "i e_next"))
def _(spark, d):
    return union([_tag(spectrum.good_turing(spectrum.spectrum(sampling.bernoulli(load(spark, d, s), 0.1))), s) for s in SPEC])


@query("g4_empirical_prob", sql(f"SELECT element, f, f / sum(f) OVER () AS prob FROM ({duck.counts(duck.sample(S('cust_key'), 0.1))})", "prob"))
def _(spark, d):
    return spectrum.empirical_prob(sampling.bernoulli(load(spark, d, "cust_key"), 0.1))


def _unseen(s: str, rate: float = 0.1) -> str:
    return (f"SELECT count(*) AS n, CAST(sum(f) AS BIGINT) AS length, count(*) FILTER (NOT seen) AS unseen_values, CAST(coalesce(sum(f) FILTER (NOT seen), 0) AS BIGINT) AS unseen_rows, "
            f"coalesce(sum(f) FILTER (NOT seen), 0) / sum(f) AS p0_mass, count(*) FILTER (NOT seen) / count(*) AS p0_distinct "
            f"FROM (SELECT f, element IN (SELECT element FROM ({duck.sample(S(s), rate)})) AS seen FROM ({duck.counts(S(s))}))")


@query("g5_unseen_truth", sql(tagged({s: _unseen(s) for s in SPEC}), "p0_mass p0_distinct"))
def _(spark, d):
    out = []
    for s in SPEC:
        x = load(spark, d, s)
        out.append(_tag(spectrum.unseen_truth(x, sampling.bernoulli(x, 0.1)), s))
    return union(out)


# --- probes ---

def _probe(name: str, mode: str, u: int, rate: float = 0.1, names=("order_key", "cust_key"), boundary: str = "keep"):
    @query(name, sql(tagged({s: duck.probe(duck.sample(S(s), rate), u, mode, boundary=boundary) for s in names}), "p0 p1", "u u1 u2"))
    def _(spark, d):
        return union([_tag(probe.probe(sampling.bernoulli(load(spark, d, s), rate), u, mode, boundary=boundary), s) for s in names])


_probe("r1_probe_in_sub", "in_sub", 200)
_probe("r2_probe_in_sample", "in_sample", 200)
_probe("r3_probe_value_hash", "value_hash", 200)
_probe("r3_probe_value_hash_drop", "value_hash", 200, boundary="drop")
_probe("r5_u_ge_l", "value_hash", 1_000_000, names=("cust_key", "host"))


@query("r3_probe_grouped", sql(duck.probe(duck.sample(S("part_key", {"flag": "l_returnflag"}), 0.1), 300, "value_hash", ["flag"]), "p0 p1", "u u1 u2"))
def _(spark, d):
    return probe.probe(sampling.bernoulli(load(spark, d, "part_key", {"flag": "l_returnflag"}), 0.1), 300, group_by=["flag"])


@query("r4_reservoir_cost")
def _(spark, d):
    cost = probe.reservoir_cost(load(spark, d, "part_key"), 100)
    return cost.agg(F.sum("seen").alias("seen"), F.sum("insertions").alias("insertions"), F.sum("expected").alias("expected"), F.count(F.lit(1)).alias("tasks"))


@query("r6_classic_reservoir", "SELECT least(100, count(*)) AS u FROM lineitem")
def _(spark, d):
    """Random keys: another subsample under another partitioning, always of u occurrences."""
    return probe.reservoir(load(spark, d, "part_key"), 100, "random").agg(F.count(F.lit(1)).alias("u"))


@query("r6_reservoir", tagged({k: f"SELECT element, {duck.h60(chr(39).join(['occ || ', '|u42', '']))} AS occ_hash, {duck.h60(chr(39).join(['element || ', '|v42', '']))} AS value_hash FROM ({S('order_key')}) ORDER BY {o} LIMIT 300" for k, o in (("value", "value_hash, occ_hash"), ("occ", "occ_hash"))}, "keys"))
def _(spark, d):
    """The set U of the one-pass reservoir with replacement of the highest key."""
    x = load(spark, d, "order_key")
    return union([_tag(probe.reservoir(x, 300, k), k, "keys") for k in ("value", "occ")])


# --- the coverage estimators ---

@query("m1_sampled", duck.m1(duck.sample(S("part_key"), 0.1), 200, 0.1))
def _(spark, d):
    return estimators.estimate_from(load(spark, d, "part_key"), 0.1, counters.HyperLogLog(200))


@query("m1_grouped", duck.m1(duck.sample(S("part_key", {"flag": "l_returnflag"}), 0.1), 200, 0.1, ["flag"]))
def _(spark, d):
    return estimators.estimate_from(load(spark, d, "part_key", {"flag": "l_returnflag"}), 0.1, counters.HyperLogLog(200), ["flag"])


@query("m1_streams", tagged({s: duck.m1(duck.sample(S(s), 0.1), 200, 0.1) for s in EVERY}))
def _(spark, d):
    return union([_tag(estimators.estimate_from(load(spark, d, s), 0.1, counters.HyperLogLog(200)), s) for s in EVERY])


M1_COUNTERS = {"exact": (counters.Exact(), None, None), "hll": (counters.HyperLogLog(500), 500, 1 / 1.08), "bottom_m": (counters.BottomM(500), 500, 1.0), "linear": (counters.Linear(4096), 4096, 1.0)}


@query("m1_counters", " UNION ALL ".join(duck.m1(duck.sample(S("order_key"), 0.1), m, 0.1, name=k, are=are) for k, (_, m, are) in M1_COUNTERS.items()))
def _(spark, d):
    return union([estimators.estimate_from(load(spark, d, "order_key"), 0.1, c) for c, _, _ in M1_COUNTERS.values()])


@query("m1_sketch_counters")
def _(spark, d):
    return union([estimators.estimate_from(load(spark, d, "order_key"), 0.1, c) for c in (counters.BuiltinHll(), counters.HllSketch(10), counters.Theta(12), counters.MaxTerm(500))])


@query("m1_rate1", duck.m1(S("cust_key"), 200, 1.0))
def _(spark, d):
    return estimators.estimate_from(load(spark, d, "cust_key"), 1.0, counters.HyperLogLog(200))


@query("m1_empty", duck.m1(f"SELECT * FROM ({S('part_key')}) WHERE false", 200, 0.1))
def _(spark, d):
    """No string is below the empty one: the rows are read and all left out, where ``false`` would be folded into a plan without a table."""
    return estimators.estimate_sampled(load(spark, d, "part_key").where("element < ''"), counters.HyperLogLog(200), rate=0.1)


@query("m1_all_singletons", duck.m1("SELECT CAST(event_id AS VARCHAR) AS element, CAST(event_id AS VARCHAR) AS occ FROM events", 200, 0.1))
def _(spark, d):
    x = streams.element_stream(streams.table(spark, d, "events"), [F.col("event_id")], [F.col("event_id")])
    return estimators.estimate_sampled(x, counters.HyperLogLog(200), rate=0.1)


@query("m1_one_value", duck.m1("SELECT CAST(n_regionkey AS VARCHAR) AS element, CAST(n_nationkey AS VARCHAR) AS occ FROM nation WHERE n_regionkey = 0", 200, 0.5))
def _(spark, d):
    x = streams.element_stream(streams.table(spark, d, "nation").where("n_regionkey = 0"), [F.col("n_regionkey")], [F.col("n_nationkey")])
    return estimators.estimate_sampled(x, counters.HyperLogLog(200), rate=0.5)


NULLED = "SELECT CAST(nullif(event_type, 'error') AS VARCHAR) AS element, CAST(event_id AS VARCHAR) AS occ FROM events"


@query("m1_null_policy", tagged({"skip": duck.m1(f"SELECT * FROM ({NULLED}) WHERE element IS NOT NULL", 200, None), "as_value": duck.m1(f"SELECT coalesce(element, '~null') AS element, occ FROM ({NULLED})", 200, None)}, "null_policy"))
def _(spark, d):
    e = streams.table(spark, d, "events")
    return union([_tag(estimators.estimate_sampled(streams.element_stream(e, [F.expr("nullif(event_type, 'error')")], [F.col("event_id")], null_policy=p), counters.HyperLogLog(200)), p, "null_policy") for p in ("skip", "as_value")])


@query("m2_sampled", tagged({mode: duck.m2(duck.sample(S("order_key"), 0.1), 200, 500, mode, 0.1) for mode in probe.MODES}, "probe"))
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "order_key"), 0.1)
    return union([_tag(estimators.estimate_subsampled(y, 500, counters.HyperLogLog(200), mode, rate=0.1), mode, "probe") for mode in probe.MODES])


@query("m2_grouped", duck.m2(duck.sample(S("part_key", {"flag": "l_returnflag"}), 0.1), 200, 300, "value_hash", 0.1, ["flag"]))
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "part_key", {"flag": "l_returnflag"}), 0.1)
    return estimators.estimate_subsampled(y, 300, counters.HyperLogLog(200), group_by=["flag"], rate=0.1)


@query("m2_counters", " UNION ALL ".join(duck.m2(duck.sample(S("order_key"), 0.1), m, 500, "value_hash", 0.1, name=k, are=are) for k, (_, m, are) in (M1_COUNTERS | {"linear": (None, 65536, 1.0)}).items()))
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "order_key"), 0.1)
    return union([estimators.estimate_subsampled(y, 500, c, rate=0.1) for c in (counters.Exact(), counters.HyperLogLog(500), counters.BottomM(500), counters.Linear(65536))])


@query("m2_sketch_counters")
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "order_key"), 0.1)
    return union([estimators.estimate_subsampled(y, 500, c, mode, rate=0.1).withColumn("probe", F.lit(mode)) for mode in ("in_sample", "value_hash") for c in (counters.MaxTerm(500), counters.BuiltinHll(), counters.HllSketch(10), counters.Theta(12))])


@query("m2_fused", duck.m2(duck.sample(S("order_key"), 0.1), 200, 500, "value_hash", 0.1))
def _(spark, d):
    """One scan: registers, reservoir and length folded in each task."""
    return fused.fused(sampling.bernoulli(load(spark, d, "order_key"), 0.1), 500, counters.HyperLogLog(200), 0.1, fast=False)


@query("m2_budgeted")
def _(spark, d):
    x = load(spark, d, "part_key")
    pilot = sampling.bernoulli(x, 0.02)
    return planner.estimate_budgeted(sampling.bernoulli(x, 0.1), 1000, pilot, rate=0.1)


# --- baselines ---

@query("b1_naive", sql(tagged({s: duck.hll(duck.sample(S(s), 0.1), 200) for s in LOW_SKEW}), "ns_hat"))
def _(spark, d):
    return union([_tag(estimators.naive(sampling.bernoulli(load(spark, d, s), 0.1), counters.HyperLogLog(200)), s) for s in LOW_SKEW]).withColumnRenamed("n_hat", "ns_hat")


@query("b2_full", sql(tagged({s: duck.hll(S(s), 200) for s in LOW_SKEW}), "ns_hat"))
def _(spark, d):
    return union([_tag(estimators.full(load(spark, d, s), counters.HyperLogLog(200)), s) for s in LOW_SKEW]).withColumnRenamed("n_hat", "ns_hat")


@query("b3_exact", f"SELECT flag, count(DISTINCT element) AS n, count(*) AS length FROM ({S('order_key', {'flag': 'l_returnflag'})}) GROUP BY ALL")
def _(spark, d):
    return estimators.exact(load(spark, d, "order_key", {"flag": "l_returnflag"}), ["flag"])


@query("b4_scale_up", sql(f"SELECT ns, ns / 0.1 AS n_hat FROM ({duck.heads(duck.sample(S('order_key'), 0.1))})", "n_hat"))
def _(spark, d):
    return estimators.scale_up(sampling.bernoulli(load(spark, d, "order_key"), 0.1), 0.1)


@query("b5_oracle_ratio", sql(f"SELECT n, n - unseen_values AS ns, p0_distinct, (n - unseen_values) / (1 - p0_distinct) AS n_hat FROM ({_unseen('order_key')})", "p0_distinct n_hat"))
def _(spark, d):
    x = load(spark, d, "order_key")
    return estimators.oracle_ratio(x, sampling.bernoulli(x, 0.1))


@query("b6_skew_aware", sql(
    "SELECT ns, e1, e2, ns + CAST(e1 AS DOUBLE) * e1 / nullif(2.0 * e2, 0) AS lower_bound, ns / (1 - e1 / l) AS coverage, greatest(ns / (1 - e1 / l) * pairs / (CAST(l AS DOUBLE) * (l - 1)) - 1, 0) AS cv2, "
    "ns / (1 - e1 / l) + l * (e1 / l) / (1 - e1 / l) * greatest(ns / (1 - e1 / l) * pairs / (CAST(l AS DOUBLE) * (l - 1)) - 1, 0) AS coverage_cv "
    f"FROM (SELECT {duck.HEADS}, sum(f * (f - 1)) AS pairs FROM ({duck.counts(duck.sample(S('order_key'), 0.1))}))", "lower_bound coverage cv2 coverage_cv"))
def _(spark, d):
    return estimators.skew_aware(sampling.bernoulli(load(spark, d, "order_key"), 0.1))


# --- accuracy and cost ---

def _moments(spark, d, names=EVERY, rates=RATES) -> DataFrame:
    return union([_tag(theory.moments_at(spectrum.counts(load(spark, d, s)), rates), s) for s in names])


def _moments_sql(names=EVERY, rates=RATES) -> str:
    return " UNION ALL ".join(f"SELECT '{s}' AS stream, CAST({r!r} AS DOUBLE) AS rate, * FROM ({duck.moments(S(s), r)})" for s in names for r in rates)


@query("v_moments", sql(_moments_sql(), "p0 p1 p0_mass p1_mass"))
def _(spark, d):
    return _moments(spark, d)


@query("v_expected", sql(f"SELECT stream, rate, n, 1 - p0 AS naive, (1 - p0) / (1 - p0_mass) AS sampled FROM ({_moments_sql()})", "naive sampled"))
def _(spark, d):
    """Expected naive and corrected estimates, as shares of n."""
    m = _moments(spark, d)
    return m.select("stream", "rate", "n", (1 - F.col("p0")).alias("naive"), theory.expected_estimate(F.lit(1.0), F.col("p0"), F.col("p0_mass")).alias("sampled"))


def _moments_of_sql(names, rates, form="exact") -> str:
    return " UNION ALL ".join(f"SELECT '{s}' AS stream, CAST({r!r} AS DOUBLE) AS rate, * FROM ({duck.moments_of(duck.counts(S(s)), r, form)})" for s in names for r in rates)


@query("v_moments_exponential", sql(f"SELECT stream, rate, e.p0 AS p0_exp, e.p1 AS p1_exp, x.p0 AS p0_exact, x.p1 AS p1_exact FROM ({_moments_of_sql(EVERY, RATES, 'exp')}) e JOIN ({_moments_of_sql(EVERY, RATES)}) x USING (stream, rate)", "p0_exp p1_exp p0_exact p1_exact"))
def _(spark, d):
    """The published exponential forms beside the exact ones: alike at small rates."""
    out = []
    for s in EVERY:
        freqs = spectrum.counts(load(spark, d, s))
        e, x = (theory.moments_at(freqs, RATES, f).select("rate", F.col("p0").alias(f"p0_{f}"), F.col("p1").alias(f"p1_{f}")) for f in ("exp", "exact"))
        out.append(_tag(e.join(x, "rate"), s))
    return union(out)


@query("v_expected_subsampled", sql(
    "SELECT stream, rate, (1 - p0) / (1 - p0_mass) * (1 + p0_mass * (1 - p0_mass) / 100 / ((1 - p0_mass) * (1 - p0_mass))) AS in_sample, "
    "(1 - p0) / (1 - p0_mass) * (1 + (p0_mass * (1 - 2 * p0_mass) + p0_mass * p0_mass * square) / 100 / ((1 - p0_mass) * (1 - p0_mass))) AS value_hash "
    f"FROM ({_moments_of_sql(EVERY, [0.1])})", "in_sample value_hash"))
def _(spark, d):
    """Expected subsampled estimates of two probes with u = 100, as shares of n."""
    out, r = [], 0.1
    for s in EVERY:
        freqs = spectrum.counts(load(spark, d, s))
        k = r * F.col("f")
        square = freqs.agg((F.sum(k * (1 - r) + k * k) / (r * F.sum("f"))).alias("square"))
        m = theory.moments_at(freqs, [r]).crossJoin(F.broadcast(square))
        p = [F.lit(1.0), F.col("p0"), F.col("p0_mass"), 100]
        out.append(_tag(m.select("rate", theory.expected_subsampled(*p).alias("in_sample"), theory.expected_subsampled(*p, F.col("square")).alias("value_hash")), s))
    return union(out)


GRID_M = [50, 100, 150, 200, 500]


def _grid(df: DataFrame) -> DataFrame:
    return df.select("*", F.explode(F.array(*[F.lit(m) for m in GRID_M])).alias("m")).withColumn("u", F.lit(200) - F.least("m", F.lit(190)))


GRID_SQL = f"(SELECT *, 200 - least(m, 190) AS u FROM ({_moments_sql()}), (SELECT unnest({GRID_M}) AS m))"


@query("v_th1", sql(f"SELECT stream, rate, m, (p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0)) / (length * rate) + 1 / m AS rel_var FROM {GRID_SQL}", "rel_var", "m"))
def _(spark, d):
    g = _grid(_moments(spark, d))
    return g.select("stream", "rate", "m", theory.rel_var_sampled(F.col("p0"), F.col("p1"), F.col("length") * F.col("rate"), F.col("m")).alias("rel_var"))


@query("v_th2", sql(f"SELECT stream, rate, m, u, (2 * p0 * (1 - p0) + p1) / u / ((1 - p0) * (1 - p0)) + 1 / m AS rel_var, ((p0 * (1 - p0) + p1) / (length * rate) + p0 * (1 - p0) / u) / ((1 - p0) * (1 - p0)) + 1 / m AS two_term FROM {GRID_SQL}", "rel_var two_term", "m u"))
def _(spark, d):
    g = _grid(_moments(spark, d))
    a = [F.col(c) for c in ("p0", "p1", "u", "m")]
    return g.select("stream", "rate", "m", "u", theory.rel_var_subsampled(*a).alias("rel_var"), theory.rel_var_subsampled(*a, l=F.col("length") * F.col("rate"), form="two_term").alias("two_term"))


@query("v_th3", sql(" UNION ALL ".join(f"SELECT stream, rate, m, u, '{k}' AS procedure, (2 * p0 * (1 - p0) + p1) / u / ((1 - p0) * (1 - p0)) + 1 / ({a!r} * m) AS rel_var FROM {GRID_SQL}" for k, a in theory.ARE.items()), "rel_var", "m u"))
def _(spark, d):
    g = _grid(_moments(spark, d))
    return union([g.select("stream", "rate", "m", "u", F.lit(k).alias("procedure"), theory.rel_var_subsampled(F.col("p0"), F.col("p1"), F.col("u"), F.col("m"), a).alias("rel_var")) for k, a in theory.ARE.items()])


@query("v_product_delta", sql(
    "SELECT stream, rate, m, ns * ratio AS mean, (ratio * ratio * ns * ns / m + ns * ns * rv) / (n * n) AS var_product, (ratio * ratio * ns * ns / m + ns * ns * rv + ns * ns / m * rv) / (n * n) AS var_exact, cov "
    "FROM (SELECT *, n * (1 - p0) AS ns, 1 / (1 - p0) AS ratio, (p0 * (1 - p0) + p1) / (length * rate) / pow(1 - p0, 4) AS rv, (p0 * (1 - p0) + p1) / (length * rate) AS cov FROM " + GRID_SQL + ")", "mean var_product var_exact cov", "m"))
def _(spark, d):
    g = _grid(_moments(spark, d))
    p0, p1, l, m = F.col("p0"), F.col("p1"), F.col("length") * F.col("rate"), F.col("m")  # noqa: E741
    ns, cov = F.col("n") * (1 - p0), theory.p0_var_sampled(p0, p1, l)
    args = (ns, ns * ns / m, 1 / (1 - p0), theory.inverse_law(cov, p0))
    return g.select("stream", "rate", "m", theory.product_law(*args)[0].alias("mean"), (theory.product_law(*args)[1] / (F.col("n") * F.col("n"))).alias("var_product"), (theory.product_law(*args, exact=True)[1] / (F.col("n") * F.col("n"))).alias("var_exact"), cov.alias("cov"))


@query("v_coverage_var", sql(tagged({s: f"SELECT l, e1, e2, ((e1 + 2 * e2) / l - (e1 / l) * (e1 / l)) / l AS coverage_var, e1 / l * (1 - e1 / l) / 100 AS indicator_var, 2 * ((e1 + e2) / l - (e1 / l) * (e1 / l)) / 100 AS sub_var FROM ({duck.heads(duck.sample(S(s), 0.1))})" for s in SPEC}), "coverage_var indicator_var sub_var"))
def _(spark, d):
    out = []
    for s in SPEC:
        h = spectrum.heads(sampling.bernoulli(load(spark, d, s), 0.1))
        e1, e2, l = F.col("e1"), F.col("e2"), F.col("l")  # noqa: E741
        out.append(_tag(h.select("l", "e1", "e2", theory.coverage_var(e1, e2, l).alias("coverage_var"), theory.indicator_var(e1, l, 100).alias("indicator_var"), (2 * ((e1 + e2) / l - (e1 / l) * (e1 / l)) / 100).alias("sub_var")), s))
    return union(out)


@query("v_missing_mass_error", sql(tagged({s: f"SELECT p0_mass, e1 / l AS p0_hat, e1 / l - p0_mass AS error FROM ({_unseen(s)}), ({duck.heads(duck.sample(S(s), 0.1))})" for s in SPEC}), "p0_mass p0_hat error"))
def _(spark, d):
    out = []
    for s in SPEC:
        x = load(spark, d, s)
        y = sampling.bernoulli(x, 0.1)
        both = spectrum.unseen_truth(x, y).crossJoin(spectrum.heads(y)).withColumn("p0_hat", F.col("e1") / F.col("l"))
        out.append(_tag(both.select("p0_mass", "p0_hat", (F.col("p0_hat") - F.col("p0_mass")).alias("error")), s))
    return union(out)


@query("v_storage", sql(tagged({s: f"SELECT 200 + l AS sampled_paper, 200 + ns AS sampled_actual, 200 + 100 AS subsampled, l AS sampled_ops, 100 * (1 + ln(l / 100)) AS insertions FROM ({duck.heads(duck.sample(S(s), 0.1))}) WHERE l > 100" for s in SPEC}), "insertions", "sampled_paper sampled_actual subsampled sampled_ops"))
def _(spark, d):
    out = []
    for s in SPEC:
        h = spectrum.heads(sampling.bernoulli(load(spark, d, s), 0.1)).where("l > 100")
        out.append(_tag(h.select(theory.storage("sampled", 200, F.col("l")).alias("sampled_paper"), theory.storage("sampled", 200, ns=F.col("ns")).alias("sampled_actual"), F.lit(theory.storage("subsampled", 200, u=100)).alias("subsampled"),
                                 F.col("l").alias("sampled_ops"), (100 * (1 + F.log(F.col("l") / 100))).alias("insertions")), s))
    return union(out)


def _ci(spark, d, runs=20):
    x = load(spark, d, "part_key")
    values = workloads._per_value(workloads.sampled_runs(x, [0.1], runs))
    est = workloads.estimates_sampled(values, [200])
    n = x.agg(F.count_distinct("element").cast("double").alias("n"))
    p1 = 2 * F.col("e2") / F.col("l")
    half = 1.96 * F.sqrt(theory.rel_var_sampled(F.col("p0"), p1, F.col("l"), F.col("m"), 1 / 1.08))
    est = est.crossJoin(F.broadcast(n)).withColumn("lo", F.greatest(F.col("n_hat") * (1 - half), F.col("ns").cast("double"))).withColumn("hi", F.col("n_hat") * (1 + half))
    return est


@query("v_ci_coverage", sql(
    "SELECT rate, m, avg(CASE WHEN n BETWEEN lo AND hi THEN 1.0 ELSE 0.0 END) AS covered, avg((hi - lo) / n) AS width, covar_samp(ns_hat, 1 / (1 - p0)) / n AS covariance FROM (SELECT *, greatest(n_hat * (1 - half), CAST(ns AS DOUBLE)) AS lo, n_hat * (1 + half) AS hi FROM ("
    "SELECT *, e1 / l AS p0, 1.96 * sqrt((e1 / l * (1 - e1 / l) + 2 * e2 / l) / l / ((1 - e1 / l) * (1 - e1 / l)) + 1 / (" + repr(1 / 1.08) + " * m)) AS half FROM (" + duck.run_m1(S("part_key"), [0.1], [200], 20) + f"), (SELECT CAST(count(DISTINCT element) AS DOUBLE) AS n FROM ({S('part_key')})))) GROUP BY rate, m, n", "covered width covariance", "m"))
def _(spark, d):
    return _ci(spark, d).groupBy("rate", "m", "n").agg(
        F.avg(F.col("n").between(F.col("lo"), F.col("hi")).cast("double")).alias("covered"), F.avg((F.col("hi") - F.col("lo")) / F.col("n")).alias("width"),
        (F.covar_samp("ns_hat", 1 / (1 - F.col("p0"))) / F.col("n")).alias("covariance")).drop("n")


# --- planning ---

BUDGETS = [100, 500, 1000]


def _c(p0="p0", p1="p1") -> str:
    return f"((2 * {p0} * (1 - {p0}) + {p1}) / ((1 - {p0}) * (1 - {p0})))"


@query("k1_best_split", sql(
    f"SELECT stream, rate, b AS budget, b - u AS m, u, c / u + 1 / (b - u) AS rel_var FROM (SELECT *, row_number() OVER (PARTITION BY stream, rate, b ORDER BY c / u + 1 / (b - u), u) AS k FROM (SELECT *, {_c()} AS c FROM ({_moments_sql()})), (SELECT unnest({BUDGETS}) AS b), range(1, 1000) r(u) WHERE u <= b - 2) WHERE k = 1", "rel_var", "budget m u"))
def _(spark, d):
    """The closed form; the oracle tries every split."""
    g = _moments(spark, d).select("*", F.explode(F.array(*[F.lit(b) for b in BUDGETS])).alias("budget"))
    c = planner.coefficient(F.col("p0"), F.col("p1"))
    g = g.withColumn("c", c).withColumn("u", planner.best_u(F.col("budget").cast("double"), F.col("c"), F.lit(1.0)))
    return g.select("stream", "rate", "budget", (F.col("budget") - F.col("u")).alias("m"), "u", (F.col("c") / F.col("u") + 1 / (F.col("budget") - F.col("u"))).alias("rel_var"))


@query("k1_grid", sql(
    f"SELECT stream, rate, min(v) AS least, max(v) AS most, arg_min(u, v) AS u FROM (SELECT stream, rate, u, {_c()} / u + 1 / (200 - u) AS v FROM ({_moments_sql(LOW_SKEW)}), range(1, 199) r(u)) GROUP BY ALL", "least most", "u"))
def _(spark, d):
    """Brute force over all splits of 200: a range join of moments and splits."""
    g = _moments(spark, d, LOW_SKEW).crossJoin(F.broadcast(spark.range(1, 199).withColumnRenamed("id", "u")))
    g = g.withColumn("v", planner.coefficient(F.col("p0"), F.col("p1")) / F.col("u") + 1 / (200 - F.col("u")))
    return g.groupBy("stream", "rate").agg(F.min("v").alias("least"), F.max("v").alias("most"), F.min_by("u", "v").alias("u"))


TARGETS = [0.01, 0.002, 0.001]


@query("k2_budget_for_target", sql(
    f"SELECT stream, rate, target, ceil(pow(sqrt({_c()}) + 1, 2) / target) AS budget, 1 / (target - (p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0)) / (length * rate)) + length * rate AS sampled_units FROM ({_moments_sql(LOW_SKEW)}), (SELECT unnest({TARGETS}::DOUBLE[]) AS target)", "target sampled_units", "budget"))
def _(spark, d):
    """Least budgets for a target variance: what either method must store."""
    g = _moments(spark, d, LOW_SKEW).select("*", F.explode(F.array(*[F.lit(t) for t in TARGETS])).alias("target"))
    l = F.col("length") * F.col("rate")  # noqa: E741
    m1 = 1 / (F.col("target") - theory.ratio_var_sampled(F.col("p0"), F.col("p1"), l)) + l
    return g.select("stream", "rate", "target", planner.budget_column(F.col("target"), planner.coefficient(F.col("p0"), F.col("p1")), F.lit(1.0)).alias("budget"), m1.alias("sampled_units"))


@query("k3_split_sampled", sql(f"SELECT stream, budget, CASE WHEN budget - l >= 2 THEN budget - l END AS m_paper, CASE WHEN budget - ns >= 2 THEN budget - ns END AS m_actual, 1 / CASE WHEN budget - ns >= 2 THEN budget - ns END AS sketch_var FROM (" + tagged({s: duck.heads(duck.sample(S(s), 0.1)) for s in LOW_SKEW}) + "), (SELECT unnest([1000, 5000, 100000]) AS budget)", "sketch_var", "budget m_paper m_actual"))
def _(spark, d):
    """What a budget leaves the first method's counter, after the singleton count as published and as held."""
    out = []
    for s in LOW_SKEW:
        h = spectrum.heads(sampling.bernoulli(load(spark, d, s), 0.1)).select("*", F.explode(F.array(*[F.lit(b) for b in (1000, 5000, 100000)])).alias("budget"))
        m = planner.split_sampled(F.col("budget"), F.col("ns"))
        out.append(_tag(h.select("budget", planner.split_sampled(F.col("budget"), F.col("l")).alias("m_paper"), m.alias("m_actual"), (1 / m).alias("sketch_var")), s))
    return union(out)


@query("k4_pilot", sql(tagged({s: f"SELECT l, ns, e1, e2, e1 / l AS p0, 2 * e2 / l AS p1 FROM ({duck.heads(duck.sample(S(s), 0.05))})" for s in LOW_SKEW}), "p0 p1"))
def _(spark, d):
    return union([_tag(planner.pilot_moments(sampling.bernoulli(load(spark, d, s), 0.05)), s) for s in LOW_SKEW])


# --- experiment workloads ---

#: Runs of the experiments on tables, which SQL replays; the models take the reference's number.
RUNS, MODEL_RUNS, HEAVY_RUNS = 20, 200, 10
HEAVY_STREAMS = ("word", "talk_word", "value", "host")


def _runs(spark, d, s, rates, ms, runs=RUNS):
    x = load(spark, d, s)
    est = workloads.estimates_sampled(workloads.counted_runs(x, rates, runs), ms)
    return est.crossJoin(F.broadcast(x.agg(F.count_distinct("element").cast("double").alias("n"))))


def _sub_runs(spark, d, s, rates, splits, mode, runs=RUNS):
    x = load(spark, d, s)
    us = sorted({u for some in (splits.values() if isinstance(splits, dict) else [splits]) for _, u in some})
    values = workloads.counted_runs(x, rates, runs)
    probes = workloads.probe_counted(values, us) if mode == "value_hash" else workloads.probe_runs(workloads.sampled_runs(x, rates, runs), us, mode)
    est = workloads.estimates_subsampled(values, probes, splits)
    return est.crossJoin(F.broadcast(x.agg(F.count_distinct("element").cast("double").alias("n"))))


ACC = "bias abs_bias variance mean_l"


@query("w1_naive_vs_coverage", sql(" UNION ALL ".join(
    f"SELECT '{k}' AS method, * FROM ({duck.accuracy(duck.run_m1(S('part_key'), RATES, [200], RUNS), S('part_key'), 'rate, m', col)})" for k, col in (("naive", "n_naive"), ("sampled", "n_hat"))), ACC, "m runs"))
def _(spark, d):
    """The motivating example: sketching the sample against correcting it."""
    est = _runs(spark, d, "part_key", RATES, [200])
    return union([_tag(workloads.accuracy(est, F.col("n"), ["rate", "m"], c), k, "method") for k, c in (("naive", "n_naive"), ("sampled", "n_hat"))])


@query("w2_sampled_grid", sql(tagged({s: duck.accuracy(duck.run_m1(S(s), [0.1, 0.05], [50, 100, 150], RUNS), S(s), "rate, m") for s in LOW_SKEW}), ACC, "m runs"))
def _(spark, d):
    return union([_tag(workloads.accuracy(_runs(spark, d, s, [0.1, 0.05], [50, 100, 150]), F.col("n"), ["rate", "m"]), s) for s in LOW_SKEW])


SPLITS = [(10, 190), (50, 150), (100, 100), (150, 50), (190, 10)]


@query("w3_subsampled_grid", sql(tagged({mode: duck.accuracy(duck.run_m2(S("part_key"), [0.1], SPLITS, RUNS, mode), S("part_key"), "rate, m, u") for mode in probe.MODES}, "probe"), ACC, "m u runs"))
def _(spark, d):
    return union([_tag(workloads.accuracy(_sub_runs(spark, d, "part_key", [0.1], SPLITS, mode), F.col("n"), ["rate", "m", "u"]), mode, "probe") for mode in probe.MODES])


HEAVY = [(50, 1950), (100, 1900), (500, 1500), (1000, 1000), (1500, 500)]


@query("w4_heavy_tail", sql(tagged({s: duck.accuracy(duck.run_m2(S(s), [0.1], HEAVY, HEAVY_RUNS, "value_hash"), S(s), "rate, m, u") for s in HEAVY_STREAMS}), ACC, "m u runs"))
def _(spark, d):
    return union([_tag(workloads.accuracy(_sub_runs(spark, d, s, [0.1], HEAVY, "value_hash", HEAVY_RUNS), F.col("n"), ["rate", "m", "u"]), s) for s in HEAVY_STREAMS])


@query("w5_storage_sampled", sql(f"SELECT rate, m, m + mean_l AS storage, bias, variance FROM ({duck.accuracy(duck.run_m1(S('order_key'), [0.1, 0.05, 0.01], [100, 500, 1000], RUNS), S('order_key'), 'rate, m')})", "storage bias variance", "m"))
def _(spark, d):
    a = workloads.accuracy(_runs(spark, d, "order_key", [0.1, 0.05, 0.01], [100, 500, 1000]), F.col("n"), ["rate", "m"])
    return a.select("rate", "m", theory.storage("sampled", F.col("m"), F.col("mean_l")).alias("storage"), "bias", "variance")


#: The splits published for rate 1/100; ``w6_storage_best`` asks the planner for each rate.
BEST = {100: (92, 8), 500: (460, 40), 1000: (921, 79)}


@query("w6_storage_subsampled", sql(f"SELECT rate, m + u AS budget, m, u, bias, variance FROM ({duck.accuracy(duck.run_m2(S('order_key'), [0.1, 0.05], list(BEST.values()), RUNS, 'value_hash'), S('order_key'), 'rate, m, u')})", "bias variance", "budget m u"))
def _(spark, d):
    a = workloads.accuracy(_sub_runs(spark, d, "order_key", [0.1, 0.05], list(BEST.values()), "value_hash"), F.col("n"), ["rate", "m", "u"])
    return a.select("rate", (F.col("m") + F.col("u")).alias("budget"), "m", "u", "bias", "variance")


@query("w6_storage_best")
def _(spark, d):
    """The planner's split of each budget at each rate, from the stream's own frequencies, and what it measures."""
    rates = [0.1, 0.05, 0.01]
    known = {r["rate"]: (r["p0"], r["p1"]) for r in _moments(spark, d, ["order_key"], rates).collect()}
    splits = {r: [planner.best_split(b, *known[r]) for b in BUDGETS] for r in rates}
    a = workloads.accuracy(_sub_runs(spark, d, "order_key", rates, splits, "value_hash"), F.col("n"), ["rate", "m", "u"])
    c = F.coalesce(*[F.when(F.col("rate") == r, F.lit(planner.coefficient(*known[r]))) for r in rates])
    return a.select("rate", (F.col("m") + F.col("u")).alias("budget"), "m", "u", "bias", "variance", (c / F.col("u") + 1 / F.col("m")).alias("analysis"))


@query("w7_full_counter", sql(duck.accuracy(duck.run_m1(S("cust_key"), [1.0], [100, 500, 1000], RUNS), S("cust_key"), "rate, m"), ACC, "m runs"))
def _(spark, d):
    return workloads.accuracy(_runs(spark, d, "cust_key", [1.0], [100, 500, 1000]), F.col("n"), ["rate", "m"])


@query("w8_equal_variance", sql(
    f"SELECT stream, rate, target, budget, ceil(1 / (target - (p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0)) / (length * rate)) + length * rate) AS sampled, ceil(1 / (target - (p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0)) / (length * rate)) + length * rate) / budget AS times "
    f"FROM (SELECT *, ceil(pow(sqrt({_c()}) + 1, 2) / target) AS budget FROM ({_moments_sql(['part_key', 'supp_key', 'ship_date'])}), (SELECT unnest([0.011, 0.002]::DOUBLE[]) AS target))", "target times", "budget sampled"))
def _(spark, d):
    """Storage of both methods at equal variance."""
    g = _moments(spark, d, ["part_key", "supp_key", "ship_date"]).select("*", F.explode(F.array(F.lit(0.011), F.lit(0.002))).alias("target"))
    l = F.col("length") * F.col("rate")  # noqa: E741
    one = F.ceil(1 / (F.col("target") - theory.ratio_var_sampled(F.col("p0"), F.col("p1"), l)) + l)
    g = g.withColumn("budget", planner.budget_column(F.col("target"), planner.coefficient(F.col("p0"), F.col("p1")), F.lit(1.0))).withColumn("sampled", one)
    return g.select("stream", "rate", "target", "budget", F.col("sampled").cast("long").alias("sampled"), (F.col("sampled") / F.col("budget")).alias("times"))


@query("w9_moments", sql(tagged({s: f"SELECT count(*) AS n, sum(f) AS length, min(f) AS least, max(f) AS most, var_pop(f) / (avg(f) * avg(f)) AS cv2 FROM ({duck.counts(S(s))})" for s in EVERY}), "cv2", "n length least most"))
def _(spark, d):
    out = []
    for s in EVERY:
        c = spectrum.counts(load(spark, d, s))
        out.append(_tag(c.agg(F.count(F.lit(1)).alias("n"), F.sum("f").alias("length"), F.min("f").alias("least"), F.max("f").alias("most"), (F.var_pop("f") / (F.avg("f") * F.avg("f"))).alias("cv2")), s))
    return union(out)


MODEL_HASH = duck.h60("element || '|y42'")


@query("w9_models", sql(
    f"WITH v AS (SELECT CAST(c_custkey AS VARCHAR) AS element FROM customer ORDER BY c_custkey LIMIT 10000), u AS (SELECT {MODEL_HASH} / {float(SPAN)} AS x FROM v) "
    + " UNION ALL ".join(f"SELECT '{k}' AS model, count(*) AS n, sum(f) AS length, min(f) AS least, max(f) AS most FROM (SELECT CAST({e} AS BIGINT) AS f FROM u)" for k, e in (("uniform", "100 + floor(9901 * x)"), ("heavy", "floor(500 * pow(1 - x, -1 / 1.1))"))), "", "n length least most"))
def _(spark, d):
    ids = workloads.synthetic_ids(spark, d)
    out = []
    for k, f in (("uniform", workloads.uniform_frequencies(ids)), ("heavy", workloads.pareto_frequencies(ids))):
        out.append(_tag(f.agg(F.count(F.lit(1)).alias("n"), F.sum("f").alias("length"), F.min("f").alias("least"), F.max("f").alias("most")), k, "model"))
    return union(out)


def _model(spark, d, model, rates):
    ids = workloads.synthetic_ids(spark, d)
    freqs = workloads.uniform_frequencies(ids) if model == "uniform" else workloads.pareto_frequencies(ids)
    return freqs, ids.count(), workloads.model_moments(freqs, rates)


def published(spark, rows, names):
    return spark.createDataFrame([tuple(float(x) if not isinstance(x, int) else x for x in r) for r in rows], names)


def model_sampled(spark, d, runs=MODEL_RUNS, ms=(50, 100, 150), rates=(0.01, 0.001)):
    """First method on the uniform model: measured, predicted and published, side by side."""
    freqs, n, m = _model(spark, d, "uniform", list(rates))
    acc = workloads.accuracy(workloads.estimates_sampled(workloads.thinned(freqs, list(rates), runs), list(ms), True), n, ["rate", "m"])
    told = published(spark, workloads.PUBLISHED_SAMPLED, "rate double, m long, published_bias double, published_analysis double, published_simulation double")
    return workloads.with_theory(acc, m, False).join(told, ["rate", "m"], "left")


def model_subsampled(spark, d, model="uniform", mode="value_hash", runs=MODEL_RUNS):
    """Second method on either model."""
    told = workloads.PUBLISHED_SUBSAMPLED if model == "uniform" else workloads.PUBLISHED_HEAVY
    rates, splits = sorted({r[0] for r in told}), sorted({(r[1], r[2]) for r in told})
    freqs, n, m = _model(spark, d, model, rates)
    values = workloads.thinned(freqs, rates, runs)
    est = workloads.estimates_subsampled(values, workloads.probe_thinned(values, [u for _, u in splits], mode), splits, True)
    acc = workloads.accuracy(est, n, ["rate", "m", "u"])
    told = published(spark, told, "rate double, m long, u long, published_bias double, published_analysis double, published_simulation double")
    return workloads.with_theory(acc, m, True).join(told, ["rate", "m", "u"], "left")


def model_storage(spark, d, runs=MODEL_RUNS):
    """Storage against variance on the uniform model: both methods and the plain counter."""
    rates = [0.01, 0.002, 0.001]
    freqs, n, m = _model(spark, d, "uniform", rates)
    values = workloads.thinned(freqs, rates, runs)
    one = workloads.accuracy(workloads.estimates_sampled(values, [100, 500, 1000], True), n, ["rate", "m"])
    one = one.select(F.lit("sampled").alias("method"), "rate", "m", F.lit(None).cast("long").alias("u"), (F.col("m") + F.col("mean_l")).alias("storage"), "bias", "variance")
    splits = [(r[2], r[3]) for r in workloads.PUBLISHED_STORAGE_SUBSAMPLED]
    own = F.create_map(*[x for r in workloads.PUBLISHED_STORAGE_SUBSAMPLED for x in (F.lit(f"{r[0]}:{r[2]}:{r[3]}"), F.lit(True))])
    est = workloads.estimates_subsampled(values, workloads.probe_thinned(values, sorted({u for _, u in splits})), sorted(set(splits)), True)
    two = workloads.accuracy(est, n, ["rate", "m", "u"]).where(F.coalesce(F.try_element_at(own, F.concat_ws(":", F.col("rate").cast("string"), "m", "u")), F.lit(False)))
    two = two.select(F.lit("subsampled").alias("method"), "rate", "m", F.col("u").cast("long").alias("u"), (F.col("m") + F.col("u")).cast("double").alias("storage"), "bias", "variance")
    whole = freqs.select(F.lit(1.0).alias("rate"), "element", F.col("f").alias("k")).crossJoin(F.broadcast(spark.range(runs).withColumnRenamed("id", "run")))
    three = workloads.accuracy(workloads.estimates_sampled(whole, [100, 500, 1000], True), n, ["rate", "m"])
    three = three.select(F.lit("full").alias("method"), "rate", "m", F.lit(None).cast("long").alias("u"), F.col("m").cast("double").alias("storage"), "bias", "variance")
    return one.unionByName(two).unionByName(three)


query("w1_model")(lambda spark, d: _w1_model(spark, d))
query("w2_model")(lambda spark, d: model_sampled(spark, d))
query("w3_model")(lambda spark, d: model_subsampled(spark, d))
query("w3_model_in_sample")(lambda spark, d: model_subsampled(spark, d, mode="in_sample"))
query("w4_model_heavy")(lambda spark, d: model_subsampled(spark, d, "heavy"))
query("w5_w7_model_storage")(lambda spark, d: model_storage(spark, d))


def _w1_model(spark, d, runs=MODEL_RUNS):
    freqs, n, _ = _model(spark, d, "uniform", [0.001])
    est = workloads.estimates_sampled(workloads.thinned(freqs, [0.001], runs), [200], True)
    return union([_tag(workloads.accuracy(est, n, ["rate", "m"], c), k, "method") for k, c in (("naive", "n_naive"), ("sampled", "n_hat"))])


@query("w6_best_split", sql(
    f"WITH v AS (SELECT CAST(c_custkey AS VARCHAR) AS element FROM customer ORDER BY c_custkey LIMIT 10000), f AS (SELECT CAST(100 + floor(9901 * ({duck.h60("element || '|y42'")} / {float(SPAN)})) AS BIGINT) AS f FROM v), "
    "told(rate, budget, published_m, published_u, published_variance) AS (VALUES " + ", ".join(f"({r}::DOUBLE, {b}, {m}, {u}, {v}::DOUBLE)" for r, b, m, u, v in workloads.PUBLISHED_STORAGE_SUBSAMPLED) + "), "
    "m AS (" + " UNION ALL ".join(f"SELECT CAST({r!r} AS DOUBLE) AS rate, * FROM ({duck.moments_of('SELECT f FROM f', r)})" for r in (0.01, 0.002, 0.001)) + f"), t AS (SELECT told.*, {_c()} AS c FROM told JOIN m USING (rate)) "
    "SELECT rate, budget, budget - u AS m, u, analysis, published_m, published_u, published_variance FROM (SELECT *, c / u + 1 / (budget - u) AS analysis, row_number() OVER (PARTITION BY rate, budget ORDER BY c / u + 1 / (budget - u), u) AS k FROM t, range(1, 1000) r(u) WHERE u <= budget - 2) WHERE k = 1",
    "rate analysis published_variance", "budget m u published_m published_u"))
def _(spark, d):
    """Best splits of the model's moments next to the published ones."""
    _, _, m = _model(spark, d, "uniform", [0.01, 0.002, 0.001])
    told = published(spark, workloads.PUBLISHED_STORAGE_SUBSAMPLED, "rate double, budget long, published_m long, published_u long, published_variance double")
    j = told.join(m.select("rate", "p0", "p1"), "rate").withColumn("c", planner.coefficient(F.col("p0"), F.col("p1")))
    j = j.withColumn("u", planner.best_u(F.col("budget").cast("double"), F.col("c"), F.lit(1.0))).withColumn("m", F.col("budget") - F.col("u"))
    return j.select("rate", "budget", "m", "u", (F.col("c") / F.col("u") + 1 / F.col("m")).alias("analysis"), "published_m", "published_u", "published_variance")


@query("w10_flows_per_day", sql(
    f"SELECT day, l, n_hat, n_hat / lag(n_hat) OVER (ORDER BY day) AS jump, coalesce(n_hat > 1.5 * lag(n_hat) OVER (ORDER BY day), false) AS alert FROM ({duck.m1(duck.sample(S('flow', {'day': 'CAST(CAST(ts AS DATE) AS VARCHAR)'}), 0.5), 200, 0.5, ['day'])})", "jump", "l"))
def _(spark, d):
    """Distinct flows per day and alerts on a jump."""
    x = load(spark, d, "flow", {"day": "cast(cast(ts as date) as string)"})
    e = tidy(estimators.estimate_from(x, 0.5, counters.HyperLogLog(200), ["day"]))
    before = F.lag("n_hat").over(W.orderBy("day"))
    return e.select("day", "l", "n_hat", (F.col("n_hat") / before).alias("jump"), F.coalesce(F.col("n_hat") > 1.5 * before, F.lit(False)).alias("alert"))


@query("w12_unseen_words", sql(
    f"SELECT p0_mass, p0_distinct, p0_hat, n * (1 - p0_distinct) / (1 - p0_hat) AS n_hat FROM ({_unseen('word')}), (SELECT e1 / l AS p0_hat FROM ({duck.heads(duck.sample(S('word'), 0.1))}))", "p0_mass p0_distinct p0_hat n_hat"))
def _(spark, d):
    x = load(spark, d, "word")
    y = sampling.bernoulli(x, 0.1)
    h = spectrum.heads(y).select((F.col("e1") / F.col("l")).alias("p0_hat"))
    return spectrum.unseen_truth(x, y).crossJoin(h).select("p0_mass", "p0_distinct", "p0_hat", (F.col("n") * (1 - F.col("p0_distinct")) / (1 - F.col("p0_hat"))).alias("n_hat"))


# --- operators around the methods ---

_HLL = counters.HyperLogLog(200)
_CUST = "SELECT n_name AS nation, r_name AS region, c_mktsegment AS segment, CAST(CAST(o_orderdate AS DATE) AS VARCHAR) AS element FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _placed(spark, d) -> DataFrame:
    """The dates of all orders with the place and segment of their customers."""
    t = lambda n: streams.table(spark, d, n)
    return (t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey"))
            .join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
            .select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"), F.expr("cast(cast(o_orderdate as date) as string)").alias("element")))


def _levels_sql(keys: list[str], sets: list[tuple[str, ...]]) -> str:
    parts = " UNION ALL ".join("SELECT " + ", ".join(k if k in x else f"'(all)' AS {k}" for k in keys) + f", bucket, max(rank) AS rank FROM ({duck.registers(_CUST, 200, keys)}) GROUP BY ALL" for x in sets)
    return sql(f"SELECT {', '.join(keys)}, {duck.hll_formula(200)} AS ns_hat FROM (SELECT {', '.join(keys)}, count(*) AS used, sum(pow(2.0, -rank)) AS z FROM ({parts}) GROUP BY ALL)", "ns_hat")


def _levels(state: DataFrame, keys: list[str], sets: list[tuple[str, ...]]) -> DataFrame:
    """Estimates at several levels: registers of the finest are regrouped by their maxima, no rescan."""
    up = state.groupingSets([[*map(F.col, x), F.col("bucket")] for x in sets], *keys, "bucket").agg(F.max("rank").alias("rank"), *[F.grouping(k).alias(f"__{k}") for k in keys])
    return _HLL.estimate(up.select(*[F.when(F.col(f"__{k}") == 1, "(all)").otherwise(F.col(k)).alias(k) for k in keys], "bucket", "rank"), keys)


_ROLLUP, _CUBE = [("region", "nation"), ("region",), ()], [("region", "segment"), ("region",), ("segment",), ()]


@query("x_rollup_registers", _levels_sql(["region", "nation"], _ROLLUP))
def _(spark, d):
    return _levels(_HLL.state(_placed(spark, d), ["region", "nation"]), ["region", "nation"], _ROLLUP)


@query("x_cube_registers", _levels_sql(["region", "segment"], _CUBE))
def _(spark, d):
    return _levels(_HLL.state(_placed(spark, d), ["region", "segment"]), ["region", "segment"], _CUBE)


@query("x_cube_counts", "SELECT coalesce(region, '(all)') AS region, coalesce(segment, '(all)') AS segment, count(*) AS orders, count(DISTINCT element) AS n FROM (" + _CUST + ") GROUP BY CUBE (region, segment)")
def _(spark, d):
    c = _placed(spark, d).cube("region", "segment").agg(F.count(F.lit(1)).alias("orders"), F.count_distinct("element").alias("n"))
    return c.select(F.coalesce("region", F.lit("(all)")).alias("region"), F.coalesce("segment", F.lit("(all)")).alias("segment"), "orders", "n")


@query("x_register_arrays", sql(duck.hll(f"{S('user')} UNION ALL {S('cust_key')}", 200), "ns_hat"))
def _(spark, d):
    """Registers as arrays, one row a stream, merged place by place."""
    def packed(name: str, out: str) -> DataFrame:
        state = _HLL.state(load(spark, d, name)).agg(F.map_from_entries(F.collect_list(F.struct("bucket", "rank"))).alias("r"))
        return state.select(F.transform(F.sequence(F.lit(0), F.lit(199)), lambda i: F.coalesce(F.try_element_at("r", i), F.lit(0))).alias(out))
    both = packed("user", "a").crossJoin(packed("cust_key", "b")).select(F.explode(F.zip_with("a", "b", lambda x, y: F.greatest(x, y))).alias("rank"))
    return _HLL.estimate(both.where("rank > 0"))


@query("x_union_merge", sql(duck.hll(f"{S('user')} UNION ALL {S('cust_key')}", 200), "ns_hat"))
def _(spark, d):
    a, b = (_HLL.state(load(spark, d, s)) for s in ("user", "cust_key"))
    return _HLL.estimate(_HLL.merge(a, b))


_DAY = {"day": "CAST(CAST(ts AS DATE) AS VARCHAR)"}


@query("x_running_registers", sql(
    f"SELECT day, {duck.hll_formula(200)} AS ns_hat FROM (SELECT day, count(*) AS used, sum(pow(2.0, -rank)) AS z FROM (SELECT b.day, a.bucket, max(a.rank) AS rank FROM ({duck.registers(S('flow', _DAY), 200, ['day'])}) a JOIN (SELECT DISTINCT CAST(CAST(ts AS DATE) AS VARCHAR) AS day FROM events) b ON a.day <= b.day GROUP BY ALL) GROUP BY ALL)", "ns_hat"))
def _(spark, d):
    """Distinct flows since the first day, for every day: a running maximum per register."""
    state = _HLL.state(load(spark, d, "flow", {"day": "cast(cast(ts as date) as string)"}), ["day"])
    days = state.select("day").distinct()
    grid = days.crossJoin(F.broadcast(spark.range(200).select(F.col("id").cast("int").alias("bucket"))))
    w = W.partitionBy("bucket").orderBy("day").rowsBetween(W.unboundedPreceding, 0)
    running = grid.join(state, ["day", "bucket"], "left").withColumn("rank", F.max("rank").over(w)).where("rank IS NOT NULL")
    return _HLL.estimate(running.select("day", "bucket", "rank"), ["day"])


def _daily(spark, d):
    x = load(spark, d, "user", {"day": "cast(ts as date)"})
    return tidy(estimators.estimate_from(x, 0.5, _HLL, ["day"])).select("day", "n_hat")


_DAILY_SQL = f"SELECT day, n_hat FROM ({duck.m1(duck.sample(S('user', {'day': 'CAST(ts AS DATE)'}), 0.5), 200, 0.5, ['day'])})"


@query("x_asof_estimate", sql(f"SELECT e.event_id, CAST(d.day AS VARCHAR) AS day, d.n_hat FROM (SELECT event_id, CAST(ts AS DATE) AS at FROM events WHERE event_type = 'error') e ASOF JOIN ({_DAILY_SQL}) d ON e.at > d.day", "n_hat"))
def _(spark, d):
    """For each error event the last estimate of an earlier day: a few days, so a range join
    against them and the latest by ``max_by``."""
    e = streams.table(spark, d, "events").where("event_type = 'error'").select("event_id", F.expr("cast(ts as date)").alias("at"))
    j = e.join(_daily(spark, d), F.col("day") < F.col("at"))
    return j.groupBy("event_id").agg(F.max("day").cast("string").alias("day"), F.max_by("n_hat", "day").alias("n_hat"))


@query("x_interval_truth", sql(f"SELECT CAST(d.day AS VARCHAR) AS day, any_value(d.n_hat) AS n_hat, count(DISTINCT e.user_id) AS truth FROM ({_DAILY_SQL}) d JOIN events e ON e.ts >= d.day AND e.ts < d.day + INTERVAL 1 DAY GROUP BY d.day", "n_hat"))
def _(spark, d):
    """Estimates against the truth of their interval."""
    days = _daily(spark, d)
    e = streams.table(spark, d, "events").select("ts", "user_id")
    j = e.join(F.broadcast(days), (F.col("ts") >= F.col("day").cast("timestamp_ntz")) & (F.col("ts") < F.expr("cast(day as timestamp_ntz) + interval 1 day")))
    return j.groupBy(F.col("day").cast("string").alias("day")).agg(F.first("n_hat").alias("n_hat"), F.count_distinct("user_id").alias("truth"))


@query("x_semi_seen", f"SELECT count(*) AS seen FROM customer WHERE CAST(c_custkey AS VARCHAR) IN (SELECT element FROM ({duck.sample(S('cust_key'), 0.1)}))")
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "cust_key"), 0.1)
    return streams.table(spark, d, "customer").join(y, F.col("c_custkey").cast("string") == F.col("element"), "left_semi").agg(F.count(F.lit(1)).alias("seen"))


@query("x_anti_unseen", f"SELECT count(*) AS unseen FROM customer WHERE CAST(c_custkey AS VARCHAR) NOT IN (SELECT element FROM ({duck.sample(S('cust_key'), 0.1)}))")
def _(spark, d):
    y = sampling.bernoulli(load(spark, d, "cust_key"), 0.1)
    return streams.table(spark, d, "customer").join(y, F.col("c_custkey").cast("string") == F.col("element"), "left_anti").agg(F.count(F.lit(1)).alias("unseen"))


_HOUR = {"hour": "CAST(date_trunc('hour', ts) AS VARCHAR)"}


@query("x_outer_truth", sql(
    f"SELECT coalesce(t.hour, e.hour) AS hour, coalesce(t.n, 0) AS n, coalesce(e.n_hat, 0) AS n_hat, e.hour IS NULL AS missed FROM (SELECT hour, count(DISTINCT element) AS n FROM ({S('user', _HOUR)}) GROUP BY ALL) t FULL JOIN ({duck.m1(duck.sample(S('user', _HOUR), 0.05), 200, 0.05, ['hour'])}) e ON t.hour = e.hour", "n_hat"))
def _(spark, d):
    """Groups that the sample missed altogether show up beside those with an estimate."""
    x = load(spark, d, "user", {"hour": "cast(date_trunc('hour', cast(ts as timestamp)) as string)"})
    truth = estimators.exact(x, ["hour"]).select("hour", "n")
    e = tidy(estimators.estimate_from(x, 0.05, _HLL, ["hour"])).select("hour", "n_hat").withColumn("hit", F.lit(True))
    return truth.join(e, "hour", "full_outer").select("hour", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("n_hat", F.lit(0.0)).alias("n_hat"), F.col("hit").isNull().alias("missed"))


@query("x_json_key", f"SELECT count(DISTINCT element) AS n, count(*) AS length FROM (SELECT json_extract_string(props, '$.k') AS element FROM events) WHERE element IS NOT NULL")
def _(spark, d):
    e = streams.table(spark, d, "events")
    return estimators.exact(streams.element_stream(e, [F.get_json_object("props", "$.k")], [F.col("event_id")]))


@query("x_host", f"SELECT element AS host, count(*) AS pages FROM ({S('host')}) GROUP BY ALL")
def _(spark, d):
    return load(spark, d, "host").groupBy(F.col("element").alias("host")).agg(F.count(F.lit(1)).alias("pages"))


@query("x_tokens", f"SELECT element AS token, count(*) AS f FROM ({S('word')}) GROUP BY ALL")
def _(spark, d):
    return load(spark, d, "word").groupBy(F.col("element").alias("token")).agg(F.count(F.lit(1)).alias("f"))


@query("x_ngram_motif", "SELECT count(DISTINCT motif) AS n, count(*) AS length FROM (SELECT substr(text, i + 1, 8) AS motif FROM (SELECT text, unnest(range(length(text) - 7)) AS i FROM benchmark WHERE length(text) >= 8))")
def _(spark, d):
    """Distinct substrings of eight characters: the motifs of a sequence."""
    b = streams.table(spark, d, "benchmark").where("length(text) >= 8")
    m = b.select("item_id", F.posexplode(F.transform(F.sequence(F.lit(1), F.length("text") - 7), lambda i: F.substring(F.col("text"), i, F.lit(8)))).alias("pos", "motif"))
    return estimators.exact(streams.element_stream(m, [F.col("motif")], [F.col("item_id"), F.col("pos")]))


@query("x_set_ops", f"SELECT (SELECT count(*) FROM (SELECT element FROM ({S('user')}) UNION SELECT element FROM ({S('cust_key')}))) AS either, (SELECT count(*) FROM (SELECT element FROM ({S('user')}) INTERSECT SELECT element FROM ({S('cust_key')}))) AS both, (SELECT count(*) FROM (SELECT element FROM ({S('cust_key')}) EXCEPT SELECT element FROM ({S('user')}))) AS second_only")
def _(spark, d):
    a, b = (load(spark, d, s).select("element").distinct() for s in ("user", "cust_key"))
    one = lambda x, n: x.agg(F.count(F.lit(1)).alias(n))
    return one(a.union(b).distinct(), "either").crossJoin(one(a.intersect(b), "both")).crossJoin(one(b.subtract(a), "second_only"))


@query("x_set_ops_all", f"SELECT (SELECT count(*) FROM (SELECT element FROM ({S('user')}) INTERSECT ALL SELECT element FROM ({S('cust_key')}))) AS both, (SELECT count(*) FROM (SELECT element FROM ({S('cust_key')}) EXCEPT ALL SELECT element FROM ({S('user')}))) AS second_only")
def _(spark, d):
    """Multiset forms: occurrences, not values."""
    a, b = (load(spark, d, s).select("element") for s in ("user", "cust_key"))
    return a.intersectAll(b).agg(F.count(F.lit(1)).alias("both")).crossJoin(b.exceptAll(a).agg(F.count(F.lit(1)).alias("second_only")))


@query("x_window_ranks", f"SELECT element AS host, f, rank() OVER (ORDER BY f DESC) AS place, dense_rank() OVER (ORDER BY f DESC) AS level, ntile(4) OVER (ORDER BY f DESC, element) AS quarter, lead(f) OVER (ORDER BY f DESC, element) AS next_f FROM ({duck.counts(S('host'))})")
def _(spark, d):
    """Hosts by how often they occur: one row a host, so one task ranks them."""
    c = spectrum.counts(load(spark, d, "host"))
    by, tie = W.orderBy(F.desc("f")), W.orderBy(F.desc("f"), "element")
    return c.select(F.col("element").alias("host"), "f", F.rank().over(by).alias("place"), F.dense_rank().over(by).alias("level"), F.ntile(4).over(tie).alias("quarter"), F.lead("f").over(tie).alias("next_f"))


@query("x_percentiles", sql(tagged({s: f"SELECT min(f) AS least, quantile_cont(f, 0.25) AS p25, quantile_cont(f, 0.5) AS p50, quantile_cont(f, 0.9) AS p90, max(f) AS most, avg(f) AS mean, stddev_samp(f) AS sd FROM ({duck.counts(S(s))})" for s in LOW_SKEW}), "p25 p50 p90 mean sd", "least most"))
def _(spark, d):
    """Percentiles of the frequencies: aggregated by frequency first, so what meets are counts."""
    return union([_tag(spectrum.counts(load(spark, d, s)).agg(
        F.min("f").alias("least"), *[F.percentile("f", p).alias(f"p{round(100 * p)}") for p in (0.25, 0.5, 0.9)], F.max("f").alias("most"), F.avg("f").alias("mean"), F.stddev_samp("f").alias("sd")), s) for s in LOW_SKEW])


@query("x_sql_functions", sql(f"SELECT l, e1, 1.0 / (1 - e1 / l) AS ratio, e1 / l AS p0, (e1 / l * (1 - e1 / l) + 2 * e2 / l) / (l * (1 - e1 / l) * (1 - e1 / l)) + 1 / (1.0 * 200) AS v1 FROM ({duck.heads(duck.sample(S('part_key'), 0.1))})", "ratio p0 v1"))
def _(spark, d):
    sqlapi.register(spark)
    spectrum.heads(sampling.bernoulli(load(spark, d, "part_key"), 0.1)).createOrReplaceTempView("coverage_heads")
    return spark.sql("SELECT l, e1, cov_ratio(e1, l) AS ratio, p0_hat(e1, l) AS p0, rel_var_sampled(p0_hat(e1, l), 2 * e2 / l, l, 200L, 1.0D) AS v1 FROM coverage_heads")


@query("x_sql_planner", sql(
    f"SELECT stream, rate, budget, u, c / u + 1 / (budget - u) AS rel_var, n * (1 - p0) / (1 - p0_mass) AS expected FROM (SELECT *, row_number() OVER (PARTITION BY stream, rate, budget ORDER BY c / u + 1 / (budget - u), u) AS k FROM (SELECT *, {_c()} AS c FROM ({_moments_sql(LOW_SKEW)})), (SELECT unnest([5, 50, 500]) AS budget), range(1, 500) r(u) WHERE u <= budget - 2) WHERE k = 1", "rel_var expected", "budget u"))
def _(spark, d):
    """The planner as SQL functions; the oracle tries every split."""
    sqlapi.register(spark)
    _moments(spark, d, LOW_SKEW).createOrReplaceTempView("coverage_moments")
    c = "(2 * p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0))"
    return spark.sql(f"SELECT stream, rate, budget, u, rel_var_subsampled(p0, p1, u, budget - u, 1.0D) AS rel_var, expected_sampled(n, p0, p0_mass) AS expected FROM "
                     f"(SELECT *, best_u(budget, {c}, 1.0D) AS u FROM coverage_moments LATERAL VIEW explode(array(5L, 50L, 500L)) AS budget)")


@query("x_udtf_grid", sql(f"SELECT stream, rate, 200 - u AS m, u, {_c()} / u + 1 / (200 - u) AS rel_var FROM ({_moments_sql(LOW_SKEW)}), range(1, 199) r(u)", "rel_var", "m u"))
def _(spark, d):
    """Every split of 200 for the moments of the streams: a table function beside each row."""
    sqlapi.register(spark)
    _moments(spark, d, LOW_SKEW).createOrReplaceTempView("coverage_grid")
    return spark.sql("SELECT stream, rate, g.m, g.u, g.rel_var FROM coverage_grid, LATERAL variance_grid(200, p0, p1) g")


PARETO = [(0.9, 500), (1.1, 500), (1.5, 500), (2.5, 500), (1.1, 50)]


@query("x_pareto_grid", sql(
    f"WITH v AS (SELECT CAST(c_custkey AS VARCHAR) AS element FROM customer ORDER BY c_custkey LIMIT 10000), x AS (SELECT {MODEL_HASH} / {float(SPAN)} AS x FROM v) "
    + " UNION ALL ".join(f"SELECT {a!r}::DOUBLE AS alpha, {c} AS scale, n, length, p0, p0_mass FROM ({duck.moments_of(f'SELECT CAST(floor({c} * pow(1 - x, -1 / {a!r})) AS BIGINT) AS f FROM x', 0.001)})" for a, c in PARETO), "alpha p0 p0_mass", "scale n length"))
def _(spark, d):
    """The heavy-tailed model over shapes and scales, infinite mean included."""
    ids = workloads.synthetic_ids(spark, d)
    return union([theory.moments_at(workloads.pareto_frequencies(ids, alpha=a, scale=c), [0.001]).select(F.lit(a).alias("alpha"), F.lit(c).alias("scale"), "n", "length", "p0", "p0_mass") for a, c in PARETO])


from ..streaming import live  # noqa: E402  (its queries need the ones above)

live.add_queries(query, sql)
