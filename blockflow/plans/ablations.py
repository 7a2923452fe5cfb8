"""The seventeen configurations on a truth set derived from the documents, and what follows from them."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockflow.config import SAMPLE_TAU
from blockflow.operators import evaluate as E
from blockflow.operators import features, flowvec, similarity
from blockflow.plans import ablation_sql as Q
from blockflow.plans import graph_sql as G
from blockflow.plans.base import query
from blockflow.session import materialize
from blockflow.sources import carriers


def truth(spark: SparkSession, d: str, order: str = "md5") -> tuple[DataFrame, DataFrame]:
    """Flow vectors and calls of the truth set, and (id, grp). Where the bases are too few for the published design, the small one."""
    func = materialize(carriers.documents(spark, d), "functions")
    small = func.groupBy("sample_id").agg(F.sum((F.size("blocks") >= 3).cast("int")).alias("big")).where("big >= 3").count() < E.ISOLATED + E.GROUPS
    made = materialize(E.truth_set(func, *((30, 20, True, 10) if small else ()), order=order), "truth")
    flows = materialize(flowvec.build(made), "flows")
    return flows, materialize(E.line_calls(made), "calls"), made.select(F.col("sample_id").alias("id"), "grp").distinct()


def scored(flows: DataFrame, calls: DataFrame, name: str, least: float = 0.9) -> DataFrame:
    """Scores of all pairs of the truth set (some hundred thousand) that reach the lowest cut."""
    cfg = E.CONFIGS[name]
    vectors = materialize(features.sample_vectors(flows, calls, cfg).withColumnRenamed("sample_id", "id"), "vectors")
    heads, members = similarity.collapse(vectors.select("id", "shape", "cls", "vec_digest"))
    heads, members = materialize(heads, "heads"), materialize(members, "members")
    near = similarity.brute(heads, cfg.metric, least=least).select("id_a", "id_b", "s")
    same = heads.select(F.col("id").alias("id_a"), F.col("id").alias("id_b"), F.lit(1.0).alias("s"))
    a, b = members.toDF("x", "id_a"), members.toDF("y", "id_b")
    return near.union(same).join(a, "id_a").join(b, "id_b").where((F.col("id_a") < F.col("id_b")) | (F.col("x") < F.col("y"))).select(F.least("x", "y").alias("id_a"), F.greatest("x", "y").alias("id_b"), "s")


def one(spark: SparkSession, d: str, name: str, order: str = "md5") -> DataFrame:
    flows, calls, groups = truth(spark, d, order)
    return E.sweep(scored(flows, calls, name), groups, E.TAUS).select(F.lit(name).alias("config"), "*")


for _name in E.CONFIGS:
    query(f"ablation_{_name}", Q.one(_name))(lambda spark, d, name=_name: one(spark, d, name))


@query("ablation_large_H3", Q.one("H3", "size"))
def ablation_large_h3(spark: SparkSession, d: str) -> DataFrame:
    """The default configuration on bases with the most functions."""
    return one(spark, d, "H3", "size")


def table_of(spark: SparkSession, d: str, names: list[str], at_once: int = 4) -> DataFrame:
    """The sweeps of several configurations on one truth set, some at a time; with wall seconds where they run one by one."""
    flows, calls, groups = truth(spark, d)
    groups = materialize(groups, "groups")

    def run(name: str) -> DataFrame:
        began = time.time()
        rows = materialize(E.sweep(scored(flows, calls, name), groups, E.TAUS), "sweep")
        return rows.select(F.lit(name).alias("config"), "*", F.lit(time.time() - began).alias("seconds"))

    with ThreadPoolExecutor(at_once) as pool:
        return reduce(DataFrame.union, pool.map(run, names))


def best(rows: DataFrame) -> DataFrame:
    """Each configuration at its best cut."""
    return rows.groupBy("config").agg(F.max_by(F.struct("tau", "precision", "recall", "f1"), F.struct(F.coalesce("f1", F.lit(-1.0)), "tau")).alias("b")).select("config", "b.*")


@query("ablation_table", f"{Q.table(list(E.CONFIGS))} select * from best")
def ablation_table(spark: SparkSession, d: str) -> DataFrame:
    return best(table_of(spark, d, list(E.CONFIGS)))


@query("ablation_times")
def ablation_times(spark: SparkSession, d: str) -> DataFrame:
    """Wall seconds of the configurations on the enhancement path, one after another, samples a second, and the ratio to the one before."""
    rows = materialize(table_of(spark, d, E.PATH, 1).select("config", "seconds", F.expr("(tp + fp + fn + tn) as pairs")).distinct(), "times")
    place = F.create_map(*[F.lit(x) for n, c in enumerate(E.PATH) for x in (c, n)])
    w = Window.orderBy("place")  # a handful of rows
    n = (1 + F.sqrt(1 + 8 * F.col("pairs"))) / 2
    return rows.withColumn("place", place[F.col("config")]).select("config", "seconds", F.round(n / F.col("seconds"), 3).alias("samples_per_second"), F.round(F.col("seconds") / F.lag("seconds").over(w), 3).alias("time_ratio"))


_CHANGES = " union all ".join(f"select '{k}' as component, '{x}' as before, '{y}' as after" for k, (x, y) in E.COMPONENTS.items())
_USED = sorted({x for pair in E.COMPONENTS.values() for x in pair})


@query("ablation_contributions", f"{Q.table(_USED)}, ch as ({_CHANGES}) select component, before, after, round(q.f1 - p.f1, 6) as f1_change from ch join best p on p.config = before join best q on q.config = after")
def ablation_contributions(spark: SparkSession, d: str) -> DataFrame:
    b = materialize(best(table_of(spark, d, _USED)), "best")
    pairs = spark.createDataFrame([(k, x, y) for k, (x, y) in E.COMPONENTS.items()], "component string, before string, after string")
    j = pairs.join(b.select(F.col("config").alias("before"), F.col("f1").alias("f0")), "before").join(b.select(F.col("config").alias("after"), "f1"), "after")
    return j.select("component", "before", "after", F.round(F.col("f1") - F.col("f0"), 6).alias("f1_change"))


@query("ablation_path", f"{Q.table(E.PATH)} select * from best")
def ablation_path(spark: SparkSession, d: str) -> DataFrame:
    return best(table_of(spark, d, E.PATH))


@query("threshold_curves", f"{Q.table(E.PATH)} select config, tau, f1 from sweeps")
def threshold_curves(spark: SparkSession, d: str) -> DataFrame:
    return table_of(spark, d, E.PATH).select("config", "tau", "f1")


@query("truth_summary", f"with {Q.truth()}, g as (select grp, count(*) as k from tr group by 1) select count(*) as n_groups, cast(sum(k) as bigint) as n_samples, count(*) filter (where k = 1) as isolated, min(k) filter (where k > 1) as least, max(k) filter (where k > 1) as most, round(avg(k) filter (where k > 1), 6) as mean from g")
def truth_summary(spark: SparkSession, d: str) -> DataFrame:
    _, _, groups = truth(spark, d)
    g = groups.groupBy("grp").agg(F.count(F.lit(1)).alias("k"))
    many = F.when(F.col("k") > 1, F.col("k"))
    return g.agg(F.count(F.lit(1)).alias("n_groups"), F.sum("k").alias("n_samples"), F.sum((F.col("k") == 1).cast("int")).cast("long").alias("isolated"), F.min(many).alias("least"), F.max(many).alias("most"), F.round(F.avg(many), 6).alias("mean"))


def _split(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    flows, calls, groups = truth(spark, d)
    s = materialize(scored(flows, calls, "H3"), "scored")
    first = F.substring(F.md5("grp"), 1, 1) < "8"
    return s, groups.where(first), groups.where(~first)


_H3 = f"with recursive {Q.truth()}, {G.FLOW}, {Q.scored(E.CONFIGS['H3'])}, va as (select * from tr where substr(md5(grp), 1, 1) < '8'), te as (select * from tr where substr(md5(grp), 1, 1) >= '8')"


@query("threshold_choice", f"{_H3}, mq as (select s, x.grp = y.grp as same from sc join va x on x.id = id_a join va y on y.id = id_b), w as (select coalesce(max(s) filter (where not same), -1) as bad from mq) select min(s) as tau, count(*) as tp from mq, w where same and s > bad")
def threshold_choice(spark: SparkSession, d: str) -> DataFrame:
    s, validation, _ = _split(spark, d)
    return E.pick_threshold(s, validation)


@query("threshold_perturbation", f"{_H3} select * from {Q.swept('sc', 'te', [0.9997, 0.9998, 0.9999])}")
def threshold_perturbation(spark: SparkSession, d: str) -> DataFrame:
    s, _, test = _split(spark, d)
    return E.sweep(s, test, [0.9997, 0.9998, 0.9999])


@query("closure_pairs", f"{_H3}, e as (select id_a as a, id_b as b from sc where s >= 0.9999 union select id_b, id_a from sc where s >= 0.9999), rc(node, root) as (select a, a from e union select e.b, rc.root from rc join e on e.a = rc.node), rt as (select node, min(root) as root from rc group by 1), cl as (select x.node as id_a, y.node as id_b, 1.0 as s from rt x join rt y using (root) where x.node < y.node), dr as (select id_a, id_b, s from sc where s >= 0.9999) select 'closure' as pairs, * exclude (tau) from {Q.swept('cl', 'tr', [0.9999])} union all select 'direct', * exclude (tau) from {Q.swept('dr', 'tr', [0.9999])}")
def closure_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Direct pairs at the cut against all pairs that their components imply."""
    flows, calls, groups = truth(spark, d)
    direct = materialize(scored(flows, calls, "H3").where(F.col("s") >= SAMPLE_TAU), "direct")
    implied = E.closure(direct)
    return reduce(DataFrame.union, [E.sweep(p, groups, [SAMPLE_TAU]).drop("tau").select(F.lit(k).alias("pairs"), "*") for k, p in (("closure", implied), ("direct", direct))])
