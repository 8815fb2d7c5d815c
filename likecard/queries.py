"""Registered queries: each method, variant, measure and workload on the given tables."""

from __future__ import annotations

import functools
import hashlib
import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import hashing, metrics, patterns, tiers
from .operators import bloom, catalog, classify, exact, frontier, layers, markov, tree
from .operators.baselines import catalyst, dbms, learned, ngram, sample, suffix_tree, text_index
from .operators.estimator import Estimator, EstimatorConfig, fit, fit_catalog
from .operators.layers import TierPlan
from .operators.serve import LocalModel
from .plans import planner, profile, replay, study, theory, tuning, workloads
from .sources import stringsets
from .sources.io import table
from .sources.scratch import cut, root
from .streaming import maintenance

BOUND, MAX_LEN = "1.5", 10
#: The set that stands for each kind in the queries of the method itself.
SET_OF = {"P": "doc_openers", "S": "doc_openers", "C": "turn_openers"}
PLAIN = EstimatorConfig(plan=TierPlan.uniform(3, 0.05), frontier=False, tree=False, strategy="direct", family="portable")
WALKED = EstimatorConfig(plan=TierPlan.uniform(3, 0.05), frontier=True, tree=False, family="portable")
TUNED = EstimatorConfig()

_kept: dict = {}
_locks: dict = {}


def remembered(f):
    """Keeps a result per session, as several queries build on the same tables.
    Threads that ask for the same one wait for the first."""

    @functools.wraps(f)
    def run(spark: SparkSession, sf_dir: str, *args):
        key = (f.__name__, spark.sparkContext.applicationId, sf_dir, args)
        with _locks.setdefault(key, threading.Lock()):
            if key not in _kept:
                _kept[key] = f(spark, sf_dir, *args)
            return _kept[key]

    return run


def _by_kind(spark: SparkSession, one: Callable) -> list:
    """The outcomes of one(kind) for all kinds, side by side: each is a row of
    short jobs that wait for one another and leave most cores idle."""
    return _together(spark, one, "PSC")


def _together(spark: SparkSession, one: Callable, items, at_once: int = 3) -> list:
    """The outcomes of one(item) in the order of items, a few at once: each more
    adds plans and threads to the driver's memory."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(inheritable_thread_target(spark)(one), items))


@remembered
def strings(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return cut(stringsets.load(spark, sf_dir, name))


@remembered
def _timed_keys(spark: SparkSession, sf_dir: str, kind: str, name: str) -> tuple[DataFrame, float]:
    """The catalog of a set and the seconds that its enumeration took."""
    rows, began = strings(spark, sf_dir, name), time.perf_counter()
    return cut(catalog.enumerate_keys(rows, kind, MAX_LEN)), time.perf_counter() - began


def keys(spark: SparkSession, sf_dir: str, kind: str, name: str | None = None) -> DataFrame:
    return _timed_keys(spark, sf_dir, kind, name or SET_OF[kind])[0]


@remembered
def model(spark: SparkSession, sf_dir: str, kind: str, config: EstimatorConfig):
    return fit_catalog(keys(spark, sf_dir, kind), kind, config)


@remembered
def estimator(spark: SparkSession, sf_dir: str, name: str, config: EstimatorConfig) -> Estimator:
    return fit(strings(spark, sf_dir, name), config)


def _tiered(spark, sf_dir, kind, name=None, bound=BOUND) -> DataFrame:
    k = keys(spark, sf_dir, kind, name)
    return catalog.with_tiers(k, tiers.build(bound, catalog.max_count(k)))


def _with_pid(df: DataFrame) -> DataFrame:
    return df.withColumn("pid", F.xxhash64("key"))


# -- SQL fragments ---------------------------------------------------------

FULL = tiers.build(BOUND, 1 << 40)


def sql_keys(kind: str, name: str | None = None) -> str:
    """A select of (key, n) of all literals of a set."""
    source = stringsets.sql(name or SET_OF[kind])
    if kind == "C":
        return f"select key, count(*) as n from (select distinct sid, substr(s, i, j) as key from (select sid, s, unnest(range(1, length(s) + 1)) as i from ({source})), (select unnest(range(1, {MAX_LEN + 1})) as j) where i + j - 1 <= length(s)) group by key"
    s = "reverse(s)" if kind == "S" else "s"
    return f"select substr({s}, 1, i) as key, count(*) as n from (select s, unnest(range(1, least(length(s), {MAX_LEN}) + 1)) as i from ({source})) group by 1"


def sql_tiered(kind: str, name: str | None = None) -> str:
    return f"select key, length(key) as len, n, {FULL.tier_sql('n')} as tier from ({sql_keys(kind, name)})"


def sql_est(tier: str) -> str:
    return f"round({FULL.rep_sql(tier)}, 6)"


QUERIES: dict = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


# -- enumeration, tiers, statistics ----------------------------------------

for _name, _kind in (("keys_prefix", "P"), ("keys_suffix", "S"), ("keys_substring", "C")):
    query(_name, f"select key, cast(length(key) as int) as len, n from ({sql_keys(_kind)})")(lambda spark, d, k=_kind: keys(spark, d, k))

query("keys_prefix_rollup", ORACLE["keys_prefix"])(lambda spark, d: catalog.enumerate_prefix_rollup(strings(spark, d, SET_OF["P"]), MAX_LEN))
query("keys_undeduped", ORACLE["keys_substring"])(lambda spark, d: catalog.enumerate_keys(strings(spark, d, SET_OF["C"]), "C", MAX_LEN, dedupe_first=False))


@query("keys_levelwise", f"with k as materialized ({sql_keys('P')}) select a.key, cast(length(a.key) as int) as len, a.n from k a left join k b on b.key = substr(a.key, 1, length(a.key) - 1) where length(a.key) = 1 or b.n > 2")
def keys_levelwise(spark, d):
    return catalog.enumerate_levelwise(strings(spark, d, SET_OF["P"]), "P", tiers.build(BOUND, 2).edges[0][1], MAX_LEN)


@query("keys_levelwise_substring", f"with k as materialized ({sql_keys('C')}) select a.key, cast(length(a.key) as int) as len, a.n from k a left join k b on b.key = substr(a.key, 1, length(a.key) - 1) where length(a.key) = 1 or b.n > 2")
def keys_levelwise_substring(spark, d):
    return catalog.enumerate_levelwise(strings(spark, d, SET_OF["C"]), "C", 2, MAX_LEN)


def _edges(spark: SparkSession, d: str, bound: str) -> DataFrame:
    """The tiers that the prefixes of the event properties need, with their keys."""
    k = keys(spark, d, "P", "event_props")
    s = tiers.build(bound, catalog.max_count(k))
    every = spark.createDataFrame([(i, lo, hi) for i, (lo, hi) in enumerate(s.edges, 1)], "tier int, lo long, hi long")
    counts = catalog.with_tiers(k, s).groupBy("tier").agg(F.count("*").alias("c"))
    return every.join(counts, "tier", "left").select("tier", "lo", "hi", F.round(s.rep_col(F.col("tier")), 6).alias("rep"), F.coalesce("c", F.lit(0)).alias("n_keys"))


for _b in ("1.3", "1.5", "1.7", "2.0", "2.5"):
    _sq = round(float(_b) ** 2 * 100)
    query(f"tier_edges_{_b.replace('.', '')}", f"with recursive k as materialized ({sql_keys('P', 'event_props')}), e as (select 1 as tier, 1::bigint as lo, ({_sq} // 100)::bigint as hi union all select tier + 1, hi + 1, ((hi + 1) * {_sq}) // 100 from e where hi < (select max(n) from k)) select tier, lo, hi, round(sqrt(lo * hi), 6) as rep, (select count(*) from k where n between lo and hi) as n_keys from e")(lambda spark, d, b=_b: _edges(spark, d, b))


@query("tier_shares", " union all ".join(f"select '{k}' as kind, cast(tier as int) as tier, count(*) as n_keys, round(100 * count(*) / sum(count(*)) over (), 6) as share from ({sql_tiered(k)}) group by tier" for k in "PSC"))
def tier_shares(spark, d):
    every = [_tiered(spark, d, k).withColumn("kind", F.lit(k)) for k in "PSC"]
    return profile.tier_shares(functools.reduce(DataFrame.unionByName, every))


@query("tier_shares_controls", " union all ".join(f"select '{n}' as name, '{k}' as kind, cast(tier as int) as tier, count(*) as n_keys from ({sql_tiered(k, n)}) group by tier" for n in ("part_names", "customer_names") for k in "PS"))
def tier_shares_controls(spark, d):
    every = [_tiered(spark, d, k, n).groupBy("tier").agg(F.count("*").alias("n_keys")).select(F.lit(n).alias("name"), F.lit(k).alias("kind"), "tier", "n_keys") for n in ("part_names", "customer_names") for k in "PS"]
    return functools.reduce(DataFrame.unionByName, every)


def _profile_sql(name: str) -> str:
    s = stringsets.sql(name)
    return f"select '{name}' as name, count(*) as n_rows, count(distinct s) as n_distinct, (select count(distinct substr(s, i, 1)) from (select s, unnest(range(1, length(s) + 1)) as i from ({s}))) as vocabulary, round(avg(length(s)), 6) as avg_len, cast(max(length(s)) as int) as max_len from ({s})"


@query("set_profile", " union all ".join(_profile_sql(n) for n in stringsets.SETS))
def set_profile(spark, d):
    every = [profile.describe(stringsets.load(spark, d, n)).select(F.lit(n).alias("name"), "n_rows", "n_distinct", "vocabulary", "avg_len", "max_len") for n in stringsets.SETS]
    return functools.reduce(DataFrame.unionByName, every)


@query("topk_per_tier", f"select 'P' as kind, cast(tier as int) as tier, key, n, cast(rank as int) as rank from (select *, row_number() over (partition by tier order by n desc, key) as rank from ({sql_tiered('P')})) where rank <= 3")
def topk_per_tier(spark, d):
    return profile.top_per_tier(_tiered(spark, d, "P").withColumn("kind", F.lit("P")))


@query("cube_shares", f"with k as (select 'P' as kind, tier from ({sql_tiered('P')}) union all select 'S', tier from ({sql_tiered('S')})) select coalesce(kind, 'all') as kind, cast(coalesce(tier, 0) as int) as tier, count(*) as n_keys from k group by cube (kind, tier)")
def cube_shares(spark, d):
    rows = _tiered(spark, d, "P").select(F.lit("P").alias("kind"), "tier").unionByName(_tiered(spark, d, "S").select(F.lit("S").alias("kind"), "tier"))
    return rows.cube("kind", "tier").agg(F.count("*").alias("n_keys")).select(F.coalesce("kind", F.lit("all")).alias("kind"), F.coalesce("tier", F.lit(0)).alias("tier"), "n_keys")


@query("set_ops_keys", f"with p as (select key from ({sql_keys('P')})), s as (select reverse(key) as key from ({sql_keys('S')})) select 'both' as part, count(*) as n from (select key from p intersect select key from s) union all select 'prefix_only', count(*) from (select key from p except select key from s) union all select 'either', count(*) from (select key from p union select key from s)")
def set_ops_keys(spark, d):
    p, s = keys(spark, d, "P").select("key"), keys(spark, d, "S").select(F.reverse("key").alias("key"))
    parts = [("both", p.intersect(s)), ("prefix_only", p.exceptAll(s)), ("either", p.union(s).distinct())]
    return functools.reduce(DataFrame.unionByName, [x.agg(F.count("*").alias("n")).select(F.lit(n).alias("part"), "n") for n, x in parts])


# -- classification and estimates ------------------------------------------


def _classified(spark, d, kind: str, config: EstimatorConfig, walk: bool, rule: str = "monotone") -> DataFrame:
    _, m, _ = model(spark, d, kind, config)
    rows = _with_pid(keys(spark, d, kind)).select("pid", "key")
    return (classify.walk(rows, m, rule) if walk else classify.direct(rows, m)).select("key", "tier")


for _kind in "PSC":
    _truth = f"select key, cast(tier as int) as tier from ({sql_tiered(_kind)})"
    query(f"classify_direct_{_kind}", _truth)(lambda spark, d, k=_kind: _classified(spark, d, k, PLAIN, False))
    query(f"classify_walk_{_kind}", _truth)(lambda spark, d, k=_kind: _classified(spark, d, k, WALKED, True))
    query(f"classify_min_{_kind}", _truth)(lambda spark, d, k=_kind: _classified(spark, d, k, WALKED, True, "min"))


def _estimates(spark, d, kind: str, config: EstimatorConfig = TUNED) -> DataFrame:
    scheme, m, _ = model(spark, d, kind, config)
    rows = classify.walk(_with_pid(keys(spark, d, kind)), m)
    return rows.select(patterns.canonical_key(kind, F.col("key")).alias("lit"), "n", F.round(scheme.rep_col(F.col("tier")), 6).alias("est"))


for _kind in "PSC":
    _lit = "reverse(key)" if _kind == "S" else "key"
    query(f"estimate_{_kind}", f"select {_lit} as lit, n, {sql_est('tier')} as est from ({sql_tiered(_kind)})")(lambda spark, d, k=_kind: _estimates(spark, d, k))

_lower = tiers.build(BOUND, 1 << 40, "lower_times_bound")
query("estimate_lower_rep", f"select key as lit, n, round({_lower.rep_sql('tier')}, 6) as est from ({sql_tiered('P')})")(lambda spark, d: _estimates(spark, d, "P", EstimatorConfig(rep="lower_times_bound", plan=TierPlan.uniform(4, 0.05), tree=False)))
query("estimate_fast_hash", ORACLE["estimate_P"])(lambda spark, d: _estimates(spark, d, "P", EstimatorConfig(plan=TierPlan.uniform(2, 0.05), tree=False)))
query("estimate_portable_hash", ORACLE["estimate_P"])(lambda spark, d: _estimates(spark, d, "P", EstimatorConfig(plan=TierPlan.uniform(2, 0.05), tree=False, family="portable")))
query("estimate_uniform_layers_5", ORACLE["estimate_P"])(lambda spark, d: _estimates(spark, d, "P", EstimatorConfig(plan=TierPlan(5, (0.2, 0.1, 0.1, 0.05)), tree=False)))


@query("estimate_naive_tier_one", ORACLE["classify_direct_P"])
def estimate_naive_tier_one(spark, d):
    """The naive form, which filters tier 1 as well: same answers, larger structures."""
    k = cut(_tiered(spark, d, "P"))
    built = layers.build(k, "P", TierPlan.uniform(3, 0.05), k.agg(F.max("tier")).first()[0], skip_first=False, long_lists=True)
    return classify.direct(k.select("key"), classify.KindModel("P", built))


@query("classify_by_join_build", ORACLE["classify_direct_S"])
def classify_by_join_build(spark, d):
    """Fitted and probed with word tables by joins, as when filters outgrow the driver."""
    _, m, _ = model(spark, d, "S", EstimatorConfig(plan=TierPlan.uniform(3, 0.05), frontier=False, tree=False, by_join=True))
    return classify.direct(keys(spark, d, "S").select("key"), m)


@query("frontier_keys", f"with k as materialized ({sql_tiered('P')}), up as (select key, substr(key, 1, i) as p from (select key, unnest(range(1, length(key))) as i from k where tier = 1)) select key from k where tier = 1 and key not in (select up.key from up join k on k.key = up.p where k.tier = 1)")
def frontier_keys(spark, d):
    return frontier.reduce(_tiered(spark, d, "P")).filter("tier = 1").select("key")


@query("frontier_saving", " union all ".join(f"select '{k}' as kind, (select count(*) from ({sql_tiered(k)}) where tier = 1) as ones, (select count(*) from ({sql_tiered(k)}) a left join ({sql_tiered(k)}) b on b.key = substr(a.key, 1, length(a.key) - 1) where a.tier = 1 and coalesce(b.tier, 2) > 1) as frontier" for k in "PSC"))
def frontier_saving(spark, d):
    parts = []
    for k in "PSC":
        t = _tiered(spark, d, k)
        ones = t.filter("tier = 1").agg(F.count("*").alias("ones"))
        kept = frontier.reduce(t).filter("tier = 1").agg(F.count("*").alias("frontier"))
        parts.append(ones.join(F.broadcast(kept)).select(F.lit(k).alias("kind"), "ones", "frontier"))
    return functools.reduce(DataFrame.unionByName, parts)


# -- measures ----------------------------------------------------------------


def _evaluated(spark, d, kind: str) -> DataFrame:
    scheme, m, _ = model(spark, d, kind, TUNED)
    test = workloads.split(keys(spark, d, kind)).filter("split = 'test'").select("key")
    est = classify.walk(_with_pid(test), m).withColumn("est", scheme.rep_col(F.col("tier")))
    return workloads.evaluated(est, keys(spark, d, kind)).withColumn("kind", F.lit(kind))


def _error_sql(kind: str) -> str:
    e = FULL.rep_sql("tier")
    return f"select '{kind}' as kind, key, n, tier, greatest(greatest({e}, 1) / n, n / greatest({e}, 1)) as e from ({sql_tiered(kind)}) where {workloads.digest_sql('split|', 'key')} % 3 = 0"


_quant = "count(*) as n, round(avg(e), 6) as mean, round(quantile_cont(e, 0.5), 6) as p50, round(quantile_cont(e, 0.9), 6) as p90, round(quantile_cont(e, 0.99), 6) as p99, round(max(e), 6) as max"
_errors = " union all ".join(_error_sql(k) for k in "PSC")


def _all_evaluated(spark, d):
    return functools.reduce(DataFrame.unionByName, [_evaluated(spark, d, k) for k in "PSC"])


query("error_summary", f"select kind, {_quant} from ({_errors}) group by kind")(lambda spark, d: metrics.summary(_all_evaluated(spark, d), "kind"))
query("error_by_length", f"select kind, cast(length(key) as int) as len, count(*) as n, round(avg(e), 6) as mean from ({_errors}) group by 1, 2")(lambda spark, d: metrics.by_length(_all_evaluated(spark, d), "kind"))
query("error_by_tier", f"select kind, cast(tier as int) as true_tier, count(*) as n, round(avg(e), 6) as mean from ({_errors}) group by 1, 2")(lambda spark, d: metrics.by_tier(_all_evaluated(spark, d), FULL, "kind"))


@query("grouping_sets_report", f"select coalesce(kind, 'all') as kind, cast(coalesce(len, 0) as int) as len, count(*) as n from (select kind, length(key) as len from ({_errors})) group by grouping sets ((kind), (len), ())")
def grouping_sets_report(spark, d):
    rows = functools.reduce(DataFrame.unionByName, [workloads.split(keys(spark, d, k)).filter("split = 'test'").select(F.lit(k).alias("kind"), F.length("key").alias("len")) for k in "PSC"])
    return rows.groupingSets([["kind"], ["len"], []], "kind", "len").agg(F.count("*").alias("n")).select(F.coalesce("kind", F.lit("all")).alias("kind"), F.coalesce("len", F.lit(0)).alias("len"), "n")


def _sweep_sql(bound: str) -> str:
    s = tiers.build(bound, 1 << 40)
    t = s.tier_sql("n")
    return f"select '{bound}' as bound, max({t}) as n_tiers, round(avg(greatest({s.rep_sql(t)} / n, n / {s.rep_sql(t)})), 6) as mean, round(max(greatest({s.rep_sql(t)} / n, n / {s.rep_sql(t)})), 6) as max from k"


BOUNDS = ("1.3", "1.5", "1.7", "2.0", "2.5")


@query("bound_sweep", f"with k as materialized ({sql_keys('C')}) " + " union all ".join(_sweep_sql(b) for b in BOUNDS))
def bound_sweep(spark, d):
    k, parts = keys(spark, d, "C"), []
    for b in BOUNDS:
        s = tiers.build(b, catalog.max_count(k))
        t = k.withColumn("tier", s.tier_col(F.col("n"))).withColumn("e", metrics.ratio_error(s.rep_col(F.col("tier")), F.col("n")))
        parts.append(t.agg(F.max("tier").alias("n_tiers"), F.round(F.avg("e"), 6).alias("mean"), F.round(F.max("e"), 6).alias("max")).select(F.lit(b).alias("bound"), "n_tiers", "mean", "max"))
    return functools.reduce(DataFrame.unionByName, parts)


query("workload_split", f"select kind, split, count(*) as n from (select 'P' as kind, case when {workloads.digest_sql('split|', 'key')} % 3 = 0 then 'test' else 'train' end as split from ({sql_keys('P')})) group by all")(lambda spark, d: workloads.split(keys(spark, d, "P")).groupBy(F.lit("P").alias("kind"), "split").agg(F.count("*").alias("n")))

# -- tree ---------------------------------------------------------------------

_TOP = 4
query("tree_lookup", f"select key, cast(case when tier > {_TOP} then tier else 0 end as int) as tree_tier from ({sql_tiered('P')})")(lambda spark, d: tree.lookup(keys(spark, d, "P").select("key"), tree.nodes(_tiered(spark, d, "P"), _TOP)).select("key", F.coalesce("tree_tier", F.lit(0)).alias("tree_tier")))
query("tree_nodes", f"with t as (select key, cast(tier as int) as tier, cast(row_number() over (order by length(key), key) - 1 as int) as node_id from ({sql_tiered('P')}) where tier > {_TOP}) select t.node_id, coalesce(p.node_id, -1) as parent_id, t.key, right(t.key, 1) as ch, t.tier, coalesce((select min(c.node_id) from t c where substr(c.key, 1, length(c.key) - 1) = t.key and length(c.key) > 1), -1) as first_child, t.node_id = max(t.node_id) over (partition by substr(t.key, 1, length(t.key) - 1)) as is_last from t left join t p on p.key = substr(t.key, 1, length(t.key) - 1)")(lambda spark, d: tree.nodes(_tiered(spark, d, "P"), _TOP).fillna(-1, ["parent_id", "first_child"]))


@query("tree_threshold_sizes", f"select cast(threshold as int) as threshold, (select count(*) from ({sql_tiered('P')}) where tier > threshold) as nodes from range(1, 9) r(threshold)")
def tree_threshold_sizes(spark, d):
    t = _tiered(spark, d, "P").groupBy("tier").agg(F.count("*").alias("c"))
    every = spark.range(1, 9).select(F.col("id").cast("int").alias("threshold"))
    return every.join(F.broadcast(t), t.tier > every.threshold, "left").groupBy("threshold").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("nodes"))


# -- long patterns ---------------------------------------------------------

LONG_SET = "doc_openers"
LONG_SETS = ("doc_openers", "turn_openers", "page_urls", "customer_names")


def _long_sql(kind: str) -> str:
    d = workloads.digest_sql
    rows = f"select sid as pid, s, cast(11 + {d('ln|', 'sid')} % least(10, length(s) - 10) as int) as size from ({stringsets.sql(LONG_SET)}) where length(s) > 10"
    lit = {"P": "substr(s, 1, size)", "S": "right(s, size)", "C": f"substr(s, cast(1 + {d('st|', 'pid')} % (length(s) - size + 1) as int), size)"}[kind]
    return f"select pid, {lit} as lit from ({rows})"


def _long(spark, d, kind: str) -> DataFrame:
    return workloads.long_literals(strings(spark, d, LONG_SET), kind)


query("long_windows", f"select pid, i - 1 as i, substr(lit, i, 10) as win, substr(lit, i, 9) as ctx from (select pid, lit, unnest(range(2, length(lit) - 8)) as i from ({_long_sql('P')}))")(lambda spark, d: _long(spark, d, "P").select("pid", F.posexplode(markov.windows(F.col("lit"), MAX_LEN)).alias("i", "w")).select("pid", (F.col("i") + 1).cast("long").alias("i"), "w.win", "w.ctx"))


def _long_estimates(spark, d, kind: str, clamp: bool, name: str = LONG_SET) -> DataFrame:
    """By the fitted filters and walks. Every window of these literals occurs in
    the set, and such keys are never misclassified, so SQL can check it."""
    rows = workloads.long_literals(strings(spark, d, name), kind).withColumn("key", patterns.canonical_key(kind, F.col("lit")))
    return estimator(spark, d, name, TUNED).estimate_keys(rows, kind, clamp).select("pid", "lit", "est")


def _long_est_sql(kind: str, clamp: bool) -> str:
    key = "reverse(lit)" if kind == "S" else "lit"
    turn = (lambda x: f"reverse({x})") if kind == "S" else (lambda x: x)
    ratio = "ew / ec" if not clamp else "least(1, ew / ec)"
    body = "h.est * r" if not clamp else f"greatest({FULL.value(1)!r}::double, least(h.est * r, l))"
    return (
        f"with c as materialized (select key, {FULL.rep_sql('tier')} as est from ({sql_tiered('C', LONG_SET)})), h as materialized (select key, {FULL.rep_sql('tier')} as est from ({sql_tiered(kind, LONG_SET)})), "
        f"p as materialized (select pid, lit, {key} as key from ({_long_sql(kind)})), w as (select pid, {turn('substr(key, i, 10)')} as win, {turn('substr(key, i, 9)')} as ctx from (select pid, key, unnest(range(2, length(key) - 8)) as i from p)), "
        f"r as (select pid, product({ratio}) as r, min(ew) as l from (select pid, a.est as ew, b.est as ec from w join c a on a.key = win join c b on b.key = ctx) group by pid) "
        f"select p.pid, p.lit, {body} as est from p join h on h.key = substr(p.key, 1, 10) join r on r.pid = p.pid"
    )


for _kind in "PSC":
    query(f"long_estimate_{_kind}", f"select pid, lit, round(est, 6) as est from ({_long_est_sql(_kind, False)})")(lambda spark, d, k=_kind: _long_estimates(spark, d, k, False).withColumn("est", F.round("est", 6)))
query("long_estimate_clamped", f"select pid, lit, round(est, 6) as est from ({_long_est_sql('C', True)})")(lambda spark, d: _long_estimates(spark, d, "C", True).withColumn("est", F.round("est", 6)))
query("exact_long", f"with s as materialized ({stringsets.sql(LONG_SET)}) select pid, lit, (select count(*) from s where contains(s.s, lit)) as true_n from ({_long_sql('C')})")(lambda spark, d: exact.count_patterns(strings(spark, d, LONG_SET), _long(spark, d, "C").withColumn("kind", F.lit("C"))).select("pid", "lit", "true_n"))


_fits = {"P": "starts_with(s.s, lit)", "S": "ends_with(s.s, lit)", "C": "contains(s.s, lit)"}


def _long_error_sql(kind: str, clamp: bool) -> str:
    e = "select greatest(est, 1) as est, greatest(true_n, 1) as true_n from (select est, (select count(*) from s where " + _fits[kind] + f") as true_n from ({_long_est_sql(kind, clamp)}))"
    return f"select '{kind}' as kind, '{'clamped' if clamp else 'published'}' as form, {_quant} from (select greatest(est / true_n, true_n / est) as e from ({e}))"


@query("long_error", f"with s as materialized ({stringsets.sql(LONG_SET)}) " + " union all ".join(_long_error_sql(k, c) for k in "PSC" for c in (False, True)))
def long_error(spark, d):
    """Ratio errors of long patterns, published and clamped form."""
    parts = []
    for kind in "PSC":
        for clamp in (False, True):
            est = _long_estimates(spark, d, kind, clamp).withColumn("kind", F.lit(kind))
            true = exact.count_patterns(strings(spark, d, LONG_SET), est.select("pid", "kind", "lit"))
            e = est.join(true.select("pid", "true_n"), "pid").withColumn("ratio_error", metrics.ratio_error(F.col("est"), F.col("true_n")))
            parts.append(metrics.summary(e.withColumn("form", F.lit("clamped" if clamp else "published")), "kind", "form"))
    return functools.reduce(DataFrame.unionByName, parts)


@query("long_report")
def long_report(spark, d):
    """Long patterns by set and kind: mean ratio error of the fitted model, and
    milliseconds a pattern of the local path."""
    rows = []
    for name in LONG_SETS:
        local = LocalModel(estimator(spark, d, name, TUNED))
        for kind in "PSC":
            est = _long_estimates(spark, d, kind, False, name).withColumn("kind", F.lit(kind))
            true = exact.count_patterns(strings(spark, d, name), est.select("pid", "kind", "lit"))
            e = est.join(true.select("pid", "true_n"), "pid").agg(F.count("*").alias("n"), F.avg(metrics.ratio_error(F.col("est"), F.col("true_n"))).alias("mean")).first()
            probe = [r.lit for r in est.select("lit").limit(500).collect()]
            began = time.perf_counter()
            for lit in probe:
                local.estimate_key(kind, lit)
            rows.append((name, kind, e.n, e["mean"], (time.perf_counter() - began) * 1000 / max(1, len(probe))))
    return spark.createDataFrame(rows, "name string, kind string, n long, mean double, local_ms double")


# -- patterns, empty answers, filters ---------------------------------------

#: Patterns made of the strings of a set, one form a record by its number: {e} is
#: the string with \, % and _ escaped; the others leave it raw or are bare.
LIKE_SET = "doc_openers"
_FORMS = ("{e} || '%'", "'%' || {e}", "'%' || {e} || '%'", "{e} || '\\%%'", "{e}", "replace(s, ' ', '_')", "{e} || '%' || {e}", "'%'", "''", "s || '%'", "'%' || s || '%'", "'%' || {e} || '.%'", "'%%' || {e}")


def _likes_sql() -> str:
    body = r"regexp_replace(s, '([%_\\])', '\\\1', 'g')"
    form = " ".join(f"when {i} then {f.format(e=body)}" for i, f in enumerate(_FORMS))
    return f"select sid as pid, case sid % {len(_FORMS)} {form} end as pattern from ({stringsets.sql(LIKE_SET)})"


_shape = r"'(?s)^(%?)((?:[^%_\\]|\\[%_\\])+)(%?)$'"
_parse_sql = f"select pid, pattern, case when not regexp_matches(pattern, {_shape}) then 'O' when head = '' and tail = '%' then 'P' when head = '%' and tail = '' then 'S' when head = '%' and tail = '%' then 'C' else 'O' end as kind, body from (select pid, pattern, regexp_extract(pattern, {_shape}, 1) as head, regexp_extract(pattern, {_shape}, 2) as body, regexp_extract(pattern, {_shape}, 3) as tail from ({_likes_sql()}))"
_lit_sql = r"case when kind = 'O' then null else regexp_replace(body, '\\([%_\\])', '\1', 'g') end"


def _likes_df(spark, d):
    e = F.regexp_replace("s", r"([%_\\])", r"\\$1")
    form = F.pmod("sid", F.lit(len(_FORMS)))
    any_ = F.lit("%")
    made = [F.concat(e, any_), F.concat(any_, e), F.concat(any_, e, any_), F.concat(e, F.lit("\\%%")), e, F.replace("s", F.lit(" "), F.lit("_")), F.concat(e, any_, e), any_, F.lit(""), F.concat("s", any_), F.concat(any_, "s", any_), F.concat(any_, e, F.lit(".%")), F.concat(F.lit("%%"), e)]
    pattern = made[-1]
    for i, m in enumerate(made[:-1]):
        pattern = F.when(form == i, m).otherwise(pattern)
    rows = strings(spark, d, LIKE_SET).select(F.col("sid").alias("pid"), pattern.alias("pattern"))
    return rows.withColumn("p", patterns.parse_like(F.col("pattern"))).select("pid", "pattern", "p.kind", "p.lit")


query("pattern_kinds", f"select kind, count(*) as n from ({_parse_sql}) group by kind")(lambda spark, d: _likes_df(spark, d).groupBy("kind").agg(F.count("*").alias("n")))
query("parse_escape", f"select pid, pattern, kind, {_lit_sql} as lit from ({_parse_sql})")(lambda spark, d: _likes_df(spark, d))


def _empty_sql(kind: str) -> str:
    d, name = workloads.digest_sql, SET_OF[kind]
    chars = f"(select list(ch order by ch) from (select distinct substr(s, i, 1) as ch from (select s, unnest(range(1, length(s) + 1)) as i from ({stringsets.sql(name)}))))"
    grown = " || ".join(["key"] + [f"case when n >= {r} then list_extract(chars, cast({d(f'ch{r}|', 'key')} % len(chars) + 1 as int)) else '' end" for r in range(1, 5)])
    return f"with k as materialized ({sql_keys(kind)}), c as (select {chars} as chars) select distinct grown as key from (select {grown} as grown from (select key, 1 + {d('len|', 'key')} % 4 as n, chars from k, c where {d('split|', 'key')} % 3 = 0)) where length(grown) <= {MAX_LEN} and grown not in (select key from k)"


@remembered
def empties(spark, d, kind: str) -> DataFrame:
    return cut(workloads.empty_patterns(keys(spark, d, kind), workloads.vocabulary(strings(spark, d, SET_OF[kind])), MAX_LEN))


for _kind in "PSC":
    query(f"empty_patterns_{_kind}", _empty_sql(_kind))(lambda spark, d, k=_kind: empties(spark, d, k))


def _empty_rates(spark, d, kind: str) -> list[tuple]:
    """(kind, strategy, n, tier_one, theory): each strategy is a plan of its own, for
    one of all kinds and strategies fills the driver."""
    rows, out = _with_pid(empties(spark, d, kind)), []
    _, full, _ = model(spark, d, kind, PLAIN)
    scheme, front, _ = model(spark, d, kind, WALKED)
    q = theory.fallthrough_prob([theory.hit_prob((0.05, 0.05), 3)] * len(full.filters))
    known = classify.prefix_tiers(rows, front)
    for name, found, p in (("direct", classify.direct(rows, full), q), ("walk_min", classify.walk(rows, front, "min", known), None), ("walk_monotone", classify.walk(rows, front, known=known), theory.walk_prob(q, 2, scheme.n))):
        r = found.agg(F.count("*").alias("n"), F.round(F.avg((F.col("tier") == 1).cast("double")), 6).alias("tier_one")).first()
        out.append((kind, name, r.n, r.tier_one, p))
    return out


@remembered
def _all_empty_rates(spark, d) -> list[tuple]:
    return sum(_by_kind(spark, lambda kind: _empty_rates(spark, d, kind)), [])


@query("empty_rates")
def empty_rates(spark, d):
    """Share of empty patterns that end in tier 1: plain classification on full
    negatives, and both walks on the frontier; beside the theory's value."""
    return spark.createDataFrame(_all_empty_rates(spark, d), "kind string, strategy string, n long, tier_one double, theory double")


def _tier_one_rate(spark, d, kind: str, walk: bool) -> DataFrame:
    _, m, _ = model(spark, d, kind, WALKED if walk else PLAIN)
    rows = _with_pid(empties(spark, d, kind))
    out = classify.walk(rows, m) if walk else classify.direct(rows, m)
    return out.agg(F.count("*").alias("n"), F.count_if(F.col("tier") == 1).alias("tier_one"))


_none = f"select * from ({_empty_sql('P')})"
query("empty_rate_direct", f"with empties as materialized ({_none}), {replay.build(sql_tiered('P'), 'P', False)}, {replay.probe('empties', 'P')} select count(*) as n, count(*) filter (where tier = 1) as tier_one from found")(lambda spark, d: _tier_one_rate(spark, d, "P", False))
query("empty_rate_walk", f"with empties as materialized ({_none}), {replay.build(sql_tiered('P'), 'P', True)}, {replay.walked('empties', 'P')} select count(*) as n, count(*) filter (where tier = 1) as tier_one from walk")(lambda spark, d: _tier_one_rate(spark, d, "P", True))

_FPR = 0.05


def _layer_one(spark, d):
    members = _tiered(spark, d, "P").filter("tier = 2").select("tier", "key")
    n = members.count()
    bits, hashes = bloom.sized(n, _FPR)
    f = {2: bloom.Filter(hashing.salt_of("P", 2, 1), n, bits, hashes, _FPR)}
    return cut(bloom.word_table(members, f)), f


_size_sql = f"select count(*) as n, greatest(64, ceil(-ln({_FPR}) / (ln(2) * ln(2)) * count(*)))::bigint as bits from k where tier = 2"
_spots = lambda rows: f"select key, ({hashing.portable_sql('P|2|1|', 'key')} + j * (({hashing.portable_sql('P|2|1|', 'key', 16)} | 1) % bits)) % bits as pos from {rows}, z, (select unnest(range(0, 20)) as j) where j < greatest(1, round(bits / n * ln(2)))"
_bloom_cte = f"with k as materialized ({sql_tiered('P')}), z as materialized ({_size_sql}), b as materialized (select distinct pos from ({_spots('(select key from k where tier = 2)')}))"


@query("bloom_words", f"{_bloom_cte} select pos from b")
def bloom_words(spark, d):
    """The set bits of a layer-1 filter, from its words."""
    words, _ = _layer_one(spark, d)
    bits = F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.getbit(F.col("word"), i) == 1)
    return words.select("word_idx", F.explode(bits).alias("i")).select((F.col("word_idx").cast("long") * 64 + F.col("i")).alias("pos"))


_probe_sql = f"{_bloom_cte} select key from ({_spots('(select key from k where tier = 1)')}) group by key having bool_and(pos in (select pos from b))"


@query("bloom_probe", _probe_sql)
def bloom_probe(spark, d):
    """Tier-1 keys that the layer lets pass, by expression."""
    words, f = _layer_one(spark, d)
    ready = bloom.gather(words, f)[2]
    return _tiered(spark, d, "P").filter("tier = 1").filter(ready.has_col(F.col("key"))).select("key")


@query("bloom_probe_join", _probe_sql)
def bloom_probe_join(spark, d):
    """The same by a join with the word table, nothing gathered."""
    words, f = _layer_one(spark, d)
    rest = _tiered(spark, d, "P").filter("tier = 1").select(F.lit(2).alias("tier"), "key")
    return bloom.probe_by_join(rest, words, f).select("key")


_builds = [(k, n) for k in "PSC" for n in ("full", "frontier")]


@query("layer_survivors", "with " + ", ".join(replay.build(sql_tiered(k), k, n == "frontier", name=f"{k}{n}_") for k, n in _builds) + " " + " union all ".join(replay.survivors(k, n, f"{k}{n}_") for k, n in _builds))
def layer_survivors(spark, d):
    """Keys that each layer starts from, in builds on all and on frontier negatives."""
    return _survivors(spark, d, (("full", PLAIN), ("frontier", WALKED)))


@query("layer_survivors_tuned")
def layer_survivors_tuned(spark, d):
    return _survivors(spark, d, (("tuned", TUNED),))


def _survivors(spark, d, builds) -> DataFrame:
    rows = []
    for kind in "PSC":
        for name, config in builds:
            for t, f in model(spark, d, kind, config)[1].filters.items():
                rows += [(kind, name, t, j, n) for j, n in enumerate(f.survivors, 1)]
    return spark.createDataFrame(rows, "kind string, build string, tier int, layer int, n_keys long")


@query("residual_table", "with " + ", ".join(replay.build(sql_tiered(k), k, True, name=f"{k}_") for k in "PSC") + " " + " union all ".join(f"select '{k}' as kind, cast(tier as int) as tier, key from {k}_p2" for k in "PSC"))
def residual_table(spark, d):
    parts = [layers.listed(spark, model(spark, d, k, WALKED)[1].filters).select(F.lit(k).alias("kind"), "tier", "key") for k in "PSC"]
    return functools.reduce(DataFrame.unionByName, parts)


_trace_sql = "select d.key, cast(t.tier as int) as tier, string_agg(d.tier || ':' || d.layer || ':' || d.accepted, ',' order by d.tier) filter (where t.tier = 1 or d.tier <= t.tier) as trace from decided d join t using (key) group by d.key, t.tier"


@query("classify_trace", f"with {replay.build(sql_tiered('P'), 'P', False)}, few as materialized (select key from t where length(key) <= 3), {replay.probe('few', 'P')} {_trace_sql}")
def classify_trace(spark, d):
    """For short keys the tiers asked, each as tier:deciding layer:accepted."""
    _, m, _ = model(spark, d, "P", PLAIN)
    out = classify.trace(keys(spark, d, "P").filter("len <= 3").select("key"), m)
    step = lambda s: F.concat_ws(":", s.tier.cast("string"), s.layer.cast("string"), s.accepted.cast("string"))
    return out.select("key", "tier", F.array_join(F.transform("trace", step), ",").alias("trace"))


@query("residual_exact", "select k as kind, true as holds from (values ('P'), ('S'), ('C')) v(k)")
def residual_exact(spark, d):
    """Every listed key is a member of its tier that both Bloom layers hold."""
    parts = []
    for kind in "PSC":
        filters = model(spark, d, kind, WALKED)[1].filters
        every = layers.listed(spark, filters)
        held = every.join(_tiered(spark, d, kind).select("tier", "key"), ["tier", "key"], "left_semi").select("tier", "key")
        for j in range(max((len(f.blooms) for f in filters.values()), default=0)):
            now = {t: f.blooms[j] for t, f in filters.items() if len(f.blooms) > j}
            done = held.filter(~F.col("tier").isin(*now))
            held = bloom.passing(held.filter(F.col("tier").isin(*now)), now).unionByName(done)
        n = every.agg(F.count("*").alias("n"))
        parts.append(n.join(F.broadcast(held.agg(F.count("*").alias("held")))).select(F.lit(kind).alias("kind"), (F.col("n") == F.col("held")).alias("holds")))
    return functools.reduce(DataFrame.unionByName, parts)


# -- theory and tuning -------------------------------------------------------

_FS, _MS, _QS = (0.01, 0.05, 0.1, 0.3), (2, 3, 4, 5, 6), (0.5, 0.9, 0.99)
#: The rate that a filter of k hashes over so many bits has for a tier's keys.
_fit_sql = f"select tier, r, n_keys, bits, greatest(1, round(bits / n_keys * ln(2))) as k from (select tier, r, n_keys, greatest(64, ceil(-ln(r) / (ln(2) * ln(2)) * n_keys)) as bits from (select cast(tier as int) as tier, count(*) as n_keys from ({sql_tiered('P')}) where tier > 1 group by tier), (values " + ", ".join(f"({f}::double)" for f in _FS) + ") a(r))"


@query("theory_hit_prob", f"select tier, r as rate, m, round(f, 9) as f, round(case when m % 2 = 1 then (f - f ** m) / (1 + f) else (f + f ** m) / (1 + f) end, 9) as p from (select tier, r, (1 - exp(-k * n_keys / bits)) ** k as f from ({_fit_sql})), (values " + ", ".join(f"({m})" for m in _MS) + ") b(m)")
def theory_hit_prob(spark, d):
    """Chance that a filter of m layers accepts a key of none of its sets, at the
    rates that filters sized for the tiers of the prefixes have."""
    rows = []
    for t, n in sorted(_sizes(_tiered(spark, d, "P")).items()):
        for r in _FS if t > 1 else ():
            f = theory.filter_rate(n, *bloom.sized(n, r))
            rows += [(t, r, m, round(f, 9), round(theory.hit_prob((f,) * (m - 1), m), 9)) for m in _MS]
    return spark.createDataFrame(rows, "tier int, rate double, m int, f double, p double")


_walk_sql = "1 - (1 - q) ** t * (gamma((n + t - 1)::double) / (gamma((t + 1)::double) * gamma((n - 1)::double))) / ((n - 1)::double ** t)"


@query("theory_walk_prob", " union all ".join(f"select '{k}' as kind, q, t, n, round(case when n < 2 then 1 else {_walk_sql} end, 9) as p from (select cast(max(tier) as int) as n from ({sql_tiered(k)})), (select distinct cast(length(key) as int) as t from ({sql_tiered(k)})), (values " + ", ".join(f"({q}::double)" for q in _QS) + ") a(q)" for k in "PS"))
def theory_walk_prob(spark, d):
    """Chance that a walk over the prefixes of a key ends in tier 1, for the
    lengths of keys and the number of tiers that the catalogs of prefixes and
    suffixes have, where each prefix is in tier 1 with chance q."""
    rows = []
    for kind in "PS":
        found = _tiered(spark, d, kind).groupBy("len").agg(F.max("tier").alias("top")).collect()
        n = max((r.top for r in found), default=1)
        rows += [(kind, q, r.len, n, round(theory.walk_prob(q, r.len, n), 9)) for r in found for q in _QS]
    return spark.createDataFrame(rows, "kind string, q double, t int, n int, p double")


_f = "0.05"
_sq = "(ln(2) * ln(2))"
_storage_sql = f"with c as (select cast(tier as int) as tier, count(*) as np from ({sql_tiered('P')}) group by tier), s as (select a.tier, a.np, (select sum(np) from c where c.tier = 1 or c.tier > a.tier) as nn from c a where a.tier > 1)"
query("storage_terms", f"{_storage_sql} select tier, np, nn::bigint as nn, round(-ln({_f}) / {_sq} * np, 6) as odd_bits, round(-ln({_f}) / {_sq} * nn * {_f}, 6) as even_bits, round(np * {_f} * 80, 6) as listed_bits from s")(lambda spark, d: _storage(spark, d, True))
query("storage_model", f"{_storage_sql} select m, round(sum(case m when 2 then -ln({_f}) / {_sq} * np + nn * {_f} * 80 when 3 then -ln({_f}) / {_sq} * (np + nn * {_f}) + np * {_f} * 80 else -ln({_f}) / {_sq} * (np * (1 + {_f}) + nn * {_f}) + nn * {_f} * {_f} * 80 end), 3) as bits from s, (values (2), (3), (4)) v(m) group by m")(lambda spark, d: _storage(spark, d, False))


def _sizes(df: DataFrame) -> dict[int, int]:
    return {r.tier: r["count"] for r in df.groupBy("tier").count().collect()}


def _storage(spark, d, terms: bool) -> DataFrame:
    sizes = _sizes(_tiered(spark, d, "P"))
    if not terms:
        return spark.createDataFrame([(m, round(theory.total_bits(sizes, sizes[1], MAX_LEN, 0.05, m), 3)) for m in (2, 3, 4)], "m int, bits double")
    from math import log

    per = -log(0.05) / log(2) ** 2
    rows = [(t, n, nn, round(per * n, 6), round(per * nn * 0.05, 6), round(n * 0.05 * 80, 6)) for t, n in sizes.items() if t > 1 for nn in [theory.others_of(sizes, t, sizes[1], max(sizes))]]
    return spark.createDataFrame(rows, "tier int, np long, nn long, odd_bits double, even_bits double, listed_bits double")


@query("tuned_plans")
def tuned_plans(spark, d):
    """Tuned totals by kind: tree, frontier, per-tier choice and empty_conf."""
    rows = []
    for kind in "PSC":
        t = _tiered(spark, d, kind)
        full, kept = _sizes(t), _sizes(frontier.reduce(t))
        for use_tree in (False, True):
            for name, sizes in (("full", full), ("frontier", kept)):
                for per_tier in (False, True):
                    p = tuning.optimise(sizes, MAX_LEN, tree=use_tree, per_tier=per_tier)
                    rows.append((kind, name, use_tree, per_tier, None, p.threshold, p.bits / 8))
            for conf in (0.999, 0.9999, 0.99999):
                p = tuning.optimise(kept, MAX_LEN, tree=use_tree, empty_conf=conf)
                rows.append((kind, "frontier", use_tree, False, conf, p.threshold, p.bits / 8))
    return spark.createDataFrame(rows, "kind string, negatives string, tree boolean, per_tier boolean, empty_conf double, threshold int, bytes double")


@query("empty_conf_sweep")
def empty_conf_sweep(spark, d):
    """Storage and measured share of empty patterns in tier 1, by confidence and tree."""
    rows = []
    for use_tree in (False, True):
        for conf in (None, 0.999, 0.9999, 0.99999):
            scheme, m, p = model(spark, d, "C", EstimatorConfig(tree=use_tree, empty_conf=conf))
            rate = classify.walk(_with_pid(empties(spark, d, "C")), m).agg(F.avg((F.col("tier") == 1).cast("double"))).first()[0]
            rows.append((use_tree, conf, p.bits / 8, rate))
    return spark.createDataFrame(rows, "tree boolean, empty_conf double, bytes double, tier_one double")


@query("bound_storage_sweep")
def bound_storage_sweep(spark, d):
    """By bound: build seconds, bytes and local milliseconds a pattern, kind C."""
    rows = []
    for b in BOUNDS:
        began = time.perf_counter()
        _, m, p = fit_catalog(keys(spark, d, "C"), "C", EstimatorConfig(bound=b, tree=False))
        took = time.perf_counter() - began
        probe = [r.key for r in keys(spark, d, "C").filter("len > 5").limit(300).collect()]
        began = time.perf_counter()
        for k in probe:
            m.walk(k)
        rows.append((b, took, p.bits / 8, (time.perf_counter() - began) * 1000 / max(1, len(probe))))
    return spark.createDataFrame(rows, "bound string, build_s double, bytes double, local_ms double")


@query("frontier_ablation")
def frontier_ablation(spark, d):
    rows = []
    for kind in "PSC":
        for use in (False, True):
            began = time.perf_counter()
            _, m, p = fit_catalog(keys(spark, d, kind), kind, EstimatorConfig(frontier=use, tree=False))
            rows.append((kind, use, time.perf_counter() - began, p.bits / 8, sum(f.bits / 8 + f.listed_bytes for f in m.filters.values())))
    return spark.createDataFrame(rows, "kind string, frontier boolean, build_s double, predicted_bytes double, built_bytes double")


# -- invariants ---------------------------------------------------------------


@query("bound_holds", " union all ".join(f"select '{b}' as bound, true as holds" for b in BOUNDS))
def bound_holds(spark, d):
    """By bound: whether no literal of any kind is estimated further off."""

    def worst(kind: str) -> list[float]:
        out = []
        for b in BOUNDS:
            scheme, m, _ = model(spark, d, kind, EstimatorConfig(bound=b, tree=False, plan=TierPlan.uniform(3, 0.05)))
            e = classify.walk(_with_pid(keys(spark, d, kind)), m).select(metrics.ratio_error(scheme.rep_col(F.col("tier")), F.col("n")).alias("e"))
            out.append(e.agg(F.coalesce(F.max("e"), F.lit(1.0))).first()[0])
        return out

    most = map(max, zip(*_by_kind(spark, worst)))
    return spark.createDataFrame([(b, e <= float(b) + 1e-9) for b, e in zip(BOUNDS, most)], "bound string, holds boolean")


@query("monotone_holds", "select k as kind, true as holds from (values ('P'), ('S'), ('C')) v(k)")
def monotone_holds(spark, d):
    parts = []
    for kind in "PSC":
        k = keys(spark, d, kind)
        up = k.select(F.col("key").alias("up"), F.col("n").alias("un"))
        bad = k.withColumn("up", F.expr("left(key, len - 1)")).filter("len > 1").join(up, "up").filter("un < n")
        parts.append(bad.agg((F.count("*") == 0).alias("holds")).select(F.lit(kind).alias("kind"), "holds"))
    return functools.reduce(DataFrame.unionByName, parts)


@query("walk_ge_direct", "select k as kind, true as holds from (values ('P'), ('S'), ('C')) v(k)")
def walk_ge_direct(spark, d):
    rows = {(kind, strategy): rate for kind, strategy, _, rate, _ in _all_empty_rates(spark, d)}
    return spark.createDataFrame([(k, rows[k, "walk_monotone"] >= rows[k, "direct"]) for k in "PSC"], "kind string, holds boolean")


@query("model_roundtrip", "select true as holds")
def model_roundtrip(spark, d):
    e = estimator(spark, d, "turn_openers", TUNED)
    path = f"{root(spark)}/model-{spark.sparkContext.applicationId}-{abs(hash(d)) % 10**8}"
    e.save(spark, path)
    again = Estimator.load(spark, path)
    same = all(e.models[k].filters == again.models[k].filters and e.models[k].tree == again.models[k].tree for k in e.models)
    return spark.createDataFrame([(same and e.config == again.config and e.schemes == again.schemes,)], "holds boolean")


@query("local_equals_batch", "select true as holds")
def local_equals_batch(spark, d):
    e = estimator(spark, d, "turn_openers", TUNED)
    local = LocalModel(e)
    rows = [(i, k, lit) for i, (k, lit) in enumerate((k, lit) for k in "PSC" for lit in ("The", "An", "tion", "xq", "the thing o", "ed th", "s.", ""))]
    got = {r.pid: r.est for r in e.estimate(spark.createDataFrame(rows, "pid long, kind string, lit string")).collect()}
    return spark.createDataFrame([(all(abs(got[i] - local.estimate_key(k, lit)) < 1e-9 * max(1, got[i]) for i, k, lit in rows),)], "holds boolean")


# -- baselines ----------------------------------------------------------------

query("dbms_mcv", f"select s, count(*) as w from ({stringsets.sql('doc_openers')}) group by s order by w desc, s limit 100")(lambda spark, d: dbms.mcv(strings(spark, d, "doc_openers").groupBy("s").agg(F.count("*").alias("w"))))
query("suffix_tree_nodes", f"with k as ({sql_keys('C')}) select key, n from k order by n desc, length(key), key limit (select cast(ceil(0.02 * count(*)) as bigint) from k)")(lambda spark, d: suffix_tree.kept_nodes(keys(spark, d, "C")).select("key", "n"))
query("ngram_counts", f"select gram, count(*) as n from (select distinct sid, substr(s, i, j) as gram from (select sid, s, unnest(range(1, length(s) + 1)) as i from ({stringsets.sql('turn_openers')})), (select unnest([1, 2, 3]) as j) where i + j - 1 <= length(s)) group by gram")(lambda spark, d: ngram.fit(strings(spark, d, "turn_openers")).select("gram", "n"))
_signed = "(values " + ", ".join(f"({i})" for i in range(16)) + ") m(i)"
query("ngram_signature_estimate", f"with rows as materialized ({stringsets.sql('turn_openers')}), flat as materialized (select distinct sid, substr(s, i, j) as gram from (select sid, s, unnest(range(1, length(s) + 1)) as i from rows), (select unnest([1, 2, 3]) as j) where i + j - 1 <= length(s)), ids as materialized (select sid, i, {workloads.digest_sql("' || i || '|", "sid")} as h from (select distinct sid from flat), {_signed}), "
    f"tab as materialized (select gram, i, count(*) as n, min(h) as m from flat join ids using (sid) group by gram, i), tests as materialized (select key as lit from ({sql_keys('C')}) where {workloads.digest_sql('split|', 'key')} % 3 = 0), "
    "parts as materialized (select distinct lit, case when length(lit) <= 3 then lit else substr(lit, g, 3) end as gram from (select lit, unnest(range(1, greatest(1, length(lit) - 2) + 1)) as g from tests)), "
    "met as materialized (select lit, i, count(*) as k, max(n) as most, min(m) as low, max(m) as high, arg_max(m, {'n': n, 'gram': gram}) as top from parts join tab using (gram) group by lit, i), "
    "own as (select lit, max(k) as k, max(most) as most, count(*) filter (where low = high) / 16.0::double as same, count(*) filter (where low = top) / 16.0::double as part from met group by lit) "
    "select lit, round(case when k = 1 then most::double else greatest(1.0, same * (most / greatest(part, 1 / 16.0::double))) end, 6) as est from own")(lambda spark, d: ngram.estimate(_test(spark, d, "C"), ngram.fit(strings(spark, d, "turn_openers"), sig=16, portable=True), sig=16).select("lit", F.round("est", 6).alias("est")))  # fmt: skip
query("hybrid_exact_part", f"select key as lit, n from ({sql_keys('P')}) where length(key) <= 2 and n >= 10")(lambda spark, d: _hybrid_exact(spark, d))


def _hybrid_exact(spark, d) -> DataFrame:
    """Estimates of the hybrid method where its exact part answers."""
    rows = keys(spark, d, "P").select(F.lit("P").alias("kind"), F.col("key").alias("lit"), F.col("n").alias("true_n"))
    short = keys(spark, d, "P").filter("len <= 2 and n >= 10").select(F.lit("P").alias("kind"), F.col("key").alias("lit"), "n")
    m = learned.train(rows.orderBy(F.xxhash64("lit"), "lit").limit(2000), learned.sequence_features(), linear=True, exact=short)
    return m.estimate(rows.filter("length(lit) <= 2 and true_n >= 10")).select("lit", F.round("est").cast("long").alias("n"))


def _test(spark, d, kind: str) -> DataFrame:
    rows = workloads.split(keys(spark, d, kind)).filter("split = 'test'")
    return rows.select(F.xxhash64("key").alias("pid"), F.lit(kind).alias("kind"), patterns.canonical_key(kind, F.col("key")).alias("lit"), F.col("n").alias("true_n"))


_sample = f"select * from ({stringsets.sql('doc_openers')}) where {workloads.digest_sql('smp|', 'sid')} % 100 < 1"
query("sample_estimate", f"with s as materialized ({_sample}), p as (select substr(s, 1, i) as lit, count(*) as c from (select s, unnest(range(1, least(length(s), {MAX_LEN}) + 1)) as i from s) group by 1) select key as lit, greatest(1.0, coalesce(c, 0) * 100.0)::double as est from ({sql_keys('P')}) k left join p on p.lit = k.key where {workloads.digest_sql('split|', 'key')} % 3 = 0")(lambda spark, d: sample.estimate(_test(spark, d, "P").drop("true_n"), sample.fit(strings(spark, d, "doc_openers"))).select("lit", "est"))


#: Sets of the comparison of all methods, each with three kinds.
STUDY = ("doc_words", "doc_openers", "turn_openers", "page_urls", "customer_names")


@remembered
def _study_patterns(spark, d, name: str) -> DataFrame:
    return study.patterns({k: keys(spark, d, k, name) for k in "PSC"}, strings(spark, d, name), MAX_LEN)


def _classical_makers(spark, d, name: str) -> list:
    every = {k: _timed_keys(spark, d, k, name) for k in "PSC"}
    return study.classical(strings(spark, d, name), {k: c for k, (c, _) in every.items()}, {k: s for k, (_, s) in every.items()})


def _trained_makers(spark, d, name: str) -> list:
    train = _study_patterns(spark, d, name).filter("split = 'train'")
    return study.trained(strings(spark, d, name), train, {k: keys(spark, d, k, name) for k in "PSC"})


@remembered
def _classical_rivals(spark, d, name: str) -> list:
    return [make() for make in _classical_makers(spark, d, name)]


@remembered
def _classical(spark, d, name: str):
    return study.estimates(_classical_rivals(spark, d, name), _study_patterns(spark, d, name).filter("split != 'train'"))


@remembered
def _trained(spark, d, name: str):
    return study.estimates([make() for make in _trained_makers(spark, d, name)], _study_patterns(spark, d, name).filter("split != 'train'"))


def _all_methods(spark, d, name: str) -> DataFrame:
    return _classical(spark, d, name)[0].unionByName(_trained(spark, d, name)[0])


@remembered
def _all_untimed(spark, d, name: str) -> DataFrame:
    """As _all_methods, for measures without times: methods are fitted and asked
    side by side, unless their times were taken before."""
    if all((f.__name__, spark.sparkContext.applicationId, d, (name,)) in _kept for f in (_classical, _trained)):
        return _all_methods(spark, d, name)
    _by_kind(spark, lambda k: keys(spark, d, k, name))
    asked = _study_patterns(spark, d, name).filter("split != 'train'")
    makers = _trained_makers(spark, d, name) + _classical_makers(spark, d, name)
    parts = _together(spark, lambda make: study.estimates([make()], asked)[0], makers, 2)
    return functools.reduce(DataFrame.unionByName, parts)


def _accuracy(spark, d, name: str) -> DataFrame:
    """Ratio errors of the methods without training, by kind: mean and the four
    published quantiles."""
    return metrics.summary(study.with_error(_classical(spark, d, name)[0]).withColumn("name", F.lit(name)), "name", "kind", "method")


def _accuracy_learned(spark, d, name: str) -> DataFrame:
    return metrics.summary(study.with_error(_trained(spark, d, name)[0]).withColumn("name", F.lit(name)), "name", "kind", "method")


for _name in STUDY:
    query(f"accuracy_{_name}")(lambda spark, d, n=_name: _accuracy(spark, d, n))
    query(f"accuracy_learned_{_name}")(lambda spark, d, n=_name: _accuracy_learned(spark, d, n))


@query("accuracy_by_length")
def accuracy_by_length(spark, d):
    """Mean ratio error of all methods by kind and length of the literal."""
    e = study.with_error(_all_untimed(spark, d, "turn_openers"))
    return e.groupBy("method", "kind", F.length("lit").alias("len")).agg(F.count("*").alias("n"), F.round(F.avg("ratio_error"), 6).alias("mean"))


@query("accuracy_by_cardinality")
def accuracy_by_cardinality(spark, d):
    """Mean ratio error of all methods by kind and tier of the true count."""
    e = study.with_error(_all_methods(spark, d, "turn_openers"))
    return e.groupBy("method", "kind", FULL.tier_col(F.col("true_n")).alias("true_tier")).agg(F.count("*").alias("n"), F.round(F.avg("ratio_error"), 6).alias("mean"))


def _under_two(est: DataFrame, name: str) -> DataFrame:
    none = est.filter("split = 'empty'").groupBy("method", "kind")
    return none.agg(F.count("*").alias("n"), F.round(F.avg((F.col("est") < 2).cast("double")), 6).alias("under_two")).select(F.lit(name).alias("name"), "method", "kind", "n", "under_two")


def _empty_methods(spark, d, name: str) -> DataFrame:
    """Share of empty patterns that each method estimates under 2, by kind."""
    return _under_two(_all_methods(spark, d, name), name)


for _name in STUDY:
    query(f"empty_methods_{_name}")(lambda spark, d, n=_name: _empty_methods(spark, d, n))


@remembered
def _cost_rows(spark, d, name: str) -> list[tuple]:
    rows = _classical(spark, d, name)[1] + _trained(spark, d, name)[1]
    local = LocalModel(next(r.fitted for r in _classical_rivals(spark, d, name) if r.name == "tier_filters"))
    probe = [(r.kind, r.lit) for r in _study_patterns(spark, d, name).filter("split = 'test'").select("kind", "lit").limit(1500).collect()]
    return [(name, *r, study.local_ms(local, probe) if r[0] == "tier_filters" else None) for r in rows]


def _costs(spark, d, name: str) -> DataFrame:
    """Preparation seconds, milliseconds a pattern in batches, bytes, and for our
    method the milliseconds of the local path, kinds P, S and C; by method."""
    return spark.createDataFrame(_cost_rows(spark, d, name), "name string, method string, preparation_s double, batch_ms double, bytes double, local_ms double")


for _name in STUDY:
    query(f"costs_{_name}")(lambda spark, d, n=_name: _costs(spark, d, n))


@query("capabilities")
def capabilities(spark, d):
    """What each method answers and promises, beside its measures on turn_openers."""
    est = _all_methods(spark, d, "turn_openers")
    e = study.with_error(est).groupBy("method").agg(F.avg("ratio_error").alias("accuracy"), F.percentile("ratio_error", F.lit(0.99)).alias("robustness"))
    none = est.filter("split = 'empty'").groupBy("method").agg(F.avg((F.col("est") < 2).cast("double")).alias("finds_empty"))
    cost = spark.createDataFrame([r[1:5] for r in _cost_rows(spark, d, "turn_openers")], "method string, preparation_s double, batch_ms double, bytes double")
    return profile.capabilities(spark).join(e, "method").join(none, "method", "left").join(cost, "method")


_tree_sql = f"with recursive c as materialized ({sql_keys('C')}), kept as materialized (select key, n from c order by n desc, length(key), key limit (select cast(ceil(0.02 * count(*)) as bigint) from c)), "
_tree_sql += f"tests as materialized (select key as lit from c where {workloads.digest_sql('split|', 'key')} % 3 = 0), total as (select count(*)::double as r from ({stringsets.sql('turn_openers')})), "
_tree_sql += "spans as materialized (select t.lit, s, max(e) as e from tests t, (select unnest(range(0, 10)) as s), (select unnest(range(1, 11)) as e) where s < e and e <= length(t.lit) and substr(t.lit, s + 1, e - s) in (select key from kept) group by t.lit, s), "
_tree_sql += "walk as (select lit, 0 as at, 0 as stop, r as est from tests, total union all select w.lit, coalesce(p.s, w.stop) + 1, coalesce(p.e, w.stop + 1), case when p.s is null then w.est / r else w.est * (select n from kept where key = substr(w.lit, p.s + 1, p.e - p.s)) / case when p.s < w.stop then (select n from kept where key = substr(w.lit, p.s + 1, w.stop - p.s)) else r end end "
_tree_sql += "from walk w cross join total left join lateral (select s, e from spans x where x.lit = w.lit and x.s >= w.at and x.s <= w.stop and x.e > w.stop order by s limit 1) p on true where w.stop < length(w.lit)) "
_tree_sql += "select lit, round(greatest(1.0, est), 6) as est from walk where stop >= length(lit)"


@query("suffix_tree_estimate", _tree_sql)
def suffix_tree_estimate(spark, d):
    t = suffix_tree.fit(keys(spark, d, "C"), strings(spark, d, "turn_openers").count())
    return t.estimate(_test(spark, d, "C")).select("lit", F.round("est", 6).alias("est"))


@query("catalyst_estimates")
def catalyst_estimates(spark, d):
    s, out = strings(spark, d, "doc_openers"), []
    n = s.count()
    for p in ("The%", "%ed", "%tion%"):
        out.append((p, catalyst.estimate(s, p, n), s.filter(F.col("s").like(p)).count()))
    return spark.createDataFrame(out, "pattern string, est double, true_n long")


# -- LIKE predicates, joins, streams -----------------------------------------

query("not_like", f"select count(*) as n from ({stringsets.sql('doc_openers')}) where s not like 'The%' and s not like '%ed' and s is not null")(lambda spark, d: strings(spark, d, "doc_openers").filter(~F.col("s").like("The%") & ~F.col("s").like("%ed") & F.col("s").isNotNull()).agg(F.count("*").alias("n")))
query("props_json", "select json_extract_string(props, '$.k') as k, count(*) as n from events group by 1")(lambda spark, d: table(spark, d, "events", F.get_json_object("props", "$.k").alias("k")).groupBy("k").agg(F.count("*").alias("n")))
query("join_semi_anti", "select (select count(*) from orders where o_custkey in (select c_custkey from customer where c_name like '%9')) as semi, (select count(*) from orders where o_custkey not in (select c_custkey from customer where c_name like '%9')) as anti")(lambda spark, d: _semi_anti(spark, d))


def _semi_anti(spark, d):
    orders, nine = table(spark, d, "orders", "o_custkey"), table(spark, d, "customer").filter(F.col("c_name").like("%9")).select(F.col("c_custkey").alias("o_custkey"))
    both = orders.join(nine, "o_custkey", "left_semi").agg(F.count("*").alias("semi")).join(F.broadcast(orders.join(nine, "o_custkey", "left_anti").agg(F.count("*").alias("anti"))))
    return both


_span = lambda w: f"epoch_us(time_bucket(interval '{w}', ts))"
query("event_windows_tumbling", "select epoch_us(time_bucket(interval '1 hour', ts)) as start_us, count(*) as n, count(*) filter (where props like '%9}') as matches from events group by 1")(lambda spark, d: maintenance.windowed(table(spark, d, "events"), "tumbling", late=None).select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n", "matches"))
query("event_windows_sliding", "select start_us, count(*) as n, count(*) filter (where props like '%9}') as matches from (select props, epoch_us(time_bucket(interval '15 minutes', ts)) - k * 900000000 as start_us from events, (select unnest(range(0, 4)) as k)) group by 1")(lambda spark, d: maintenance.windowed(table(spark, d, "events"), "sliding", late=None).select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n", "matches"))
query("event_windows_session", "select user_id, epoch_us(min(ts)) as start_us, count(*) as n, count(*) filter (where props like '%9}') as matches from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as g from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval '30 minutes' then 0 else 1 end as fresh from events)) group by user_id, g")(lambda spark, d: maintenance.windowed(table(spark, d, "events"), "session", late=None).select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n", "matches"))


@query("tier_crossings", f"with a as (select substr(props, 1, i) as key, count(*) as n from (select props, unnest(range(1, least(length(props), 10) + 1)) as i from events where event_id % 2 = 0) group by 1), b as (select substr(props, 1, i) as key, count(*) as n from (select props, unnest(range(1, least(length(props), 10) + 1)) as i from events) group by 1) select key, coalesce({FULL.tier_sql('a.n')}, 0) as old_tier, {FULL.tier_sql('b.n')} as new_tier from b left join a using (key) where a.n is null or {FULL.tier_sql('a.n')} <> {FULL.tier_sql('b.n')}")
def tier_crossings(spark, d):
    """Keys whose tier moved once the second half of the events came in."""
    events = table(spark, d, "events")
    old = maintenance.key_counts(events.filter("event_id % 2 = 0"))
    return maintenance.crossings(old, maintenance.merged(old, maintenance.key_counts(events.filter("event_id % 2 != 0"))), FULL)


ORACLE["tier_crossings"] = ORACLE["tier_crossings"].replace(f"coalesce({FULL.tier_sql('a.n')}, 0)", f"cast(case when a.n is null then 0 else {FULL.tier_sql('a.n')} end as int)").replace(f"{FULL.tier_sql('b.n')} as new_tier", f"cast({FULL.tier_sql('b.n')} as int) as new_tier")


@query("stream_refresh", f"select key, cast({FULL.tier_sql('n')} as int) as tier from (select substr(props, 1, i) as key, count(*) as n from (select props, unnest(range(1, least(length(props), 10) + 1)) as i from events) group by 1)")
def stream_refresh(spark, d):
    """Tiers by a model of half the events, whose stale filters were built anew
    once the other half came in."""
    events, plan = table(spark, d, "events"), TierPlan.uniform(3, 0.05)
    old, delta = (cut(maintenance.key_counts(events.filter(f"event_id % 2 {c} 0"))) for c in ("=", "!="))
    new = cut(maintenance.merged(old, delta))
    tiered = catalog.with_tiers(new, FULL).select("key", "tier")
    first = cut(catalog.with_tiers(old, FULL).select("key", "tier"))
    m = classify.KindModel("P", layers.build(first, "P", plan, first.agg(F.max("tier")).first()[0], "fast", long_lists=True))
    m = maintenance.refreshed(m, cut(tiered), cut(maintenance.crossings(old, new, FULL)), plan)
    return classify.direct(new.select("key"), m)


@query("event_versions", "select event_id, cast((select max(v.version) from (select min(ts) as ts, 1 as version from events union all select min(ts) + interval '1 day', 2 from events union all select min(ts) + interval '3 days', 3 from events) v where v.ts <= e.ts) as int) as version from events e")
def event_versions(spark, d):
    """Each event with the catalog version in force at its time."""
    events = table(spark, d, "events")
    start = events.agg(F.min("ts").alias("ts"))
    versions = start.select(F.explode(F.array(*[F.struct((F.col("ts") + F.expr(f"interval {days} days")).alias("ts"), F.lit(v).alias("version")) for v, days in ((1, 0), (2, 1), (3, 3))])).alias("x")).select("x.*")
    return maintenance.as_of(events, versions).select("event_id", "version")


def _views(spark, d) -> None:
    for t in ("nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels", "conversations"):
        table(spark, d, t).createOrReplaceTempView(t)


#: Columns whose patterns the join workload estimates, by their string set and
#: longest literal: all columns of the workload that LIKE asks about.
COLUMNS = {
    ("customer", "c_name"): ("customer_names", 10), ("part", "p_name"): ("part_names", 10), ("part", "p_type"): ("part_types", 10), ("supplier", "s_name"): ("supplier_names", 10),
    ("nation", "n_name"): ("nation_names", 10), ("events", "props"): ("event_props", 10), ("documents", "text"): ("doc_texts", 6), ("conversations", "text"): ("turn_texts", 6),
}
#: Bytes under which an estimated side is broadcast.
SMALL = 64_000.0
PLANNERS = ("catalyst_default", "tier_filters", "hybrid_frequent_gram", "compact_text_index")


@remembered
def _column_estimates(spark, d, column: tuple[str, str], method: str) -> dict[tuple[str, str], float]:
    """{(kind, literal): rows} of the workload's patterns on a column."""
    name, size = COLUMNS[column]
    asked = set()
    for spec in workloads.JOINS:
        named, _ = workloads.join_parts(spec)
        asked |= {patterns.parse_like_py(p) for t, c, p in spec[2] if (named[t], c) == column}
    asked = sorted(x for x in asked if x[0] != "O")
    kinds, s = sorted({k for k, _ in asked}), strings(spark, d, name)
    rows = spark.createDataFrame([(i, k, lit) for i, (k, lit) in enumerate(asked)], "pid long, kind string, lit string")
    if method == "tier_filters":
        need = sorted({*kinds, *(["C"] if any(len(lit) > size for _, lit in asked) else [])})
        local = LocalModel(fit(s, EstimatorConfig(kinds=tuple(need), max_len=size, plan=TierPlan.uniform(3, 0.05), tree=False)))
        return {(k, lit): local.estimate_key(k, lit) for k, lit in asked}
    if method == "hybrid_frequent_gram":
        every = {k: catalog.enumerate_keys(s, k, size) for k in kinds}
        known = functools.reduce(DataFrame.unionByName, [t.select(F.lit(k).alias("kind"), patterns.canonical_key(k, F.col("key")).alias("lit"), F.col("n")) for k, t in every.items()])
        known = cut(known)
        train = known.orderBy(F.xxhash64("kind", "lit"), "lit").limit(study.TRAIN).withColumnRenamed("n", "true_n")
        est = learned.families(train, s, known.filter("length(lit) <= 2"), iterations=5)[method]().estimate(rows)
    else:
        est = text_index.fit(s).estimate(rows)
    return {(r.kind, r.lit): r.est for r in est.collect()}


@remembered
def _table_size(spark, d, name: str) -> tuple[float, float]:
    """Rows of a table, and Catalyst's bytes a row."""
    df = table(spark, d, name)
    rows = float(df.count())
    return rows, planner.table_bytes(df) / max(1.0, rows)


def _advice(spark, d, spec, method: str) -> tuple[str, list[str] | None, float | None]:
    """(hint, order of tables, estimated rows of the first filter) of a join."""
    if method == "catalyst_default":
        return "", None, None
    named, conditions = workloads.join_parts(spec)
    sides, first = {}, None
    for alias, t in named.items():
        rows, width = _table_size(spark, d, t)
        for ft, c, p in spec[2]:
            if ft == alias and (key := patterns.parse_like_py(p))[0] != "O":
                est = min(rows, _column_estimates(spark, d, (t, c), method)[key])
                rows, first = est, est if first is None else first
        sides[alias] = planner.Side(alias, rows, width)
    order, hint = planner.advise(list(sides.values()), SMALL)
    owner = {c: alias for alias, t in named.items() for c in table(spark, d, t).columns}
    touched = lambda on: {n for n in named if f"{n}." in on} | {owner[w] for w in on.replace("=", " ").split() if w in owner}
    return hint, planner.linked_order(order, conditions, touched), first


def _join(spark, d, spec) -> DataFrame:
    _views(spark, d)
    hint, order, _ = _advice(spark, d, spec, "tier_filters")
    return spark.sql(workloads.join_sql(spec, hint, order)).select(F.round("v", 3).alias("v"))


for _i, _spec in enumerate(workloads.JOINS, 1):
    _where = " and ".join(f"{t}.{c} like '{p}'" + (" escape '\\'" if "\\" in p else "") for t, c, p in _spec[2])
    query(f"plan_query_{_i}", f"select round(cast({_spec[3]} as double), 3) as v from {_spec[1]} where {_where}")(lambda spark, d, s=_spec: _join(spark, d, s))


@query("plan_choices")
def plan_choices(spark, d):
    """Per join and method: estimated rows of its first filter and true ones, the
    hint, the order of tables, the joins that Spark ran, and the answer."""
    _views(spark, d)
    rows = []
    for i, spec in enumerate(workloads.JOINS, 1):
        t, c, p = spec[2][0]
        true = table(spark, d, workloads.join_parts(spec)[0][t]).filter(F.col(c).like(p)).count()
        for method in PLANNERS:
            hint, order, est = _advice(spark, d, spec, method)
            sql = workloads.join_sql(spec, hint, order)
            rows.append((f"plan_query_{i}", method, est, true, hint, ",".join(order or []), ",".join(planner.chosen_joins(spark, sql)), spark.sql(sql).first()[0]))
    return spark.createDataFrame(rows, "query string, method string, est double, true_n long, hint string, tables string, joins string, v double")


@query("plan_answers_agree", "select true as holds")
def plan_answers_agree(spark, d):
    """No method's plan changes the answer of a join."""
    per = plan_choices(spark, d).groupBy("query").agg((F.max("v") - F.min("v") < 1e-3).alias("same"), F.count("v").alias("n"))
    return per.agg(F.every((F.col("n") == 0) | F.col("same")).alias("holds"))


@query("plan_impact")
def plan_impact(spark, d):
    """Times of the join workload under the plans of all methods: three runs each,
    in an order shuffled by hash, after one that warms up."""
    _views(spark, d)
    texts = {(i, m): workloads.join_sql(spec, *_advice(spark, d, spec, m)[:2]) for i, spec in enumerate(workloads.JOINS, 1) for m in PLANNERS}
    for sql in texts.values():
        spark.sql(sql).collect()
    runs, rows = [(i, m, r) for i, m in texts for r in range(3)], []
    for i, m, _ in sorted(runs, key=lambda x: hashlib.md5(repr(x).encode()).digest()):
        began = time.perf_counter()
        spark.sql(texts[i, m]).collect()
        rows.append((f"plan_query_{i}", m, time.perf_counter() - began))
    return metrics.plan_impact(spark.createDataFrame(rows, "query string, method string, seconds double"), "catalyst_default")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
