"""Formulas, published numbers and equivalences of the graph fingerprints."""

from __future__ import annotations

import math
from datetime import datetime

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from blockflow.functions.taxonomy import class_sql
from blockflow.operators import alias, cleaning, dedup, flowvec, similarity
from blockflow.operators import statistics as S
from blockflow.operators.components import connected_components
from blockflow.plans import graph, registry, release
from blockflow.sources.carriers import _sentence_blocks

BLOCK = "array<struct<n:bigint,a:string,b:string,cls:array<bigint>>>"


def one_function(spark, sizes, a=None, b=None):
    a, b = a or [f"a{i}" for i in range(len(sizes))], b or [f"b{i}" for i in range(len(sizes))]
    rows = [(n, x, y, [n, 0, 0, 0, 0, 0, 0, 0, 0]) for n, x, y in zip(sizes, a, b, strict=True)]
    return spark.createDataFrame([(1, 0, "g", rows)], f"sample_id long, func_id int, grp string, blocks {BLOCK}")


def test_path_of_three_blocks(spark):
    row = flowvec.build(one_function(spark, [1, 2, 3])).first()
    assert (row.omega, row.xn, row.x, row.y) == (8, 10, 1.25, 0.625)
    assert row.cls[0] == 8 and row.zn == 0


def test_single_block_gives_zeros(spark):
    row = flowvec.build(one_function(spark, [5])).first()
    assert (row.omega, row.x, row.y, row.z, row.n_edges) == (0, 0.0, 0.0, 0.0, 0)


def test_back_edge_makes_a_loop(spark):
    row = flowvec.build(one_function(spark, [1, 1, 1], b=["p", "q", "p"])).first()
    # edges 0-1, 1-2, 2-0; all three blocks lie in the loop
    assert (row.n_edges, row.omega, row.zn) == (3, 6, 6)


def test_grid_equals_brute(spark):
    v = spark.range(60).select(
        "id",
        F.array((F.col("id") % 7) * 0.002, (F.col("id") % 5) * 0.003).alias("shape"),
        F.array(F.lit(1.0), (F.col("id") % 3) * 0.01).alias("cls"),
        F.col("id").cast("string").alias("vec_digest"),
    )
    brute = {(r.id_a, r.id_b) for r in similarity.brute(v).where("s >= 0.999").collect()}
    grid = {(r.id_a, r.id_b) for r in similarity.grid_pairs(v, 0.999).collect()}
    assert brute == grid and brute


def test_components_of_a_chain_and_a_star(spark):
    links = [(i, i + 1) for i in range(30)] + [(100, x) for x in range(101, 130)]
    roots = dict(connected_components(spark.createDataFrame(links, "a long, b long")).collect())
    assert all(roots[i] == 0 for i in range(31)) and all(roots[i] == 100 for i in range(100, 130))


@pytest.mark.parametrize(("k", "n", "low", "high"), [(1838, 1906, 95.499, 97.219), (1878, 1906, 97.884, 99.022)])
def test_published_intervals(k, n, low, high):
    a, b = S.exact_interval(k, n)
    assert math.isclose(100 * a, low, abs_tol=1e-3) and math.isclose(100 * b, high, abs_tol=1e-3)


def test_impurity_cut(spark):
    rows = [("x", "a")] * 9 + [("x", "b")] + [("y", "a")] * 8 + [("y", "b")] * 2 + [("z", "a"), ("z", "b")]
    got = {r.digest: (r.impurity, r.resolved) for r in cleaning.resolve_labels(spark.createDataFrame(rows, "digest string, grp string")).collect()}
    assert got == {"x": (0.18, "a"), "y": (0.32, "unknown"), "z": (0.5, "unknown")}


@pytest.mark.parametrize(("n", "take"), [(1, 1), (5, 5), (6, 5), (20, 10), (21, 10), (100, 30), (101, 30), (500, 75), (501, 75), (938, 76), (1500, 120), (1576, 120)])
def test_tiers(spark, n, take):
    assert spark.sql(f"select {S.TIER_SQL} as t from (select {n} as n)").first().t == take


def test_stream_sessions_equal_batch(spark, tmp_path):
    d = "/root/testdata/sf0.001"
    # a gap of 12 hours, then one of a second more; a file, as the stream picks files by name
    times = [datetime(2024, 1, 1), datetime(2024, 1, 1, 12), datetime(2024, 1, 2, 0, 0, 1)]
    pq.write_table(pa.table({"event_id": [1, 2, 3], "user_id": [7, 7, 7], "ts": pa.array(times, pa.timestamp("us"))}), tmp_path / "events.parquet")
    for at in (d, str(tmp_path)):
        e = spark.read.parquet(f"{at}/events.parquet").where("ts is not null and user_id is not null")
        batch = e.withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
        want = sorted((r.user_id, r.s, r.t, r.n) for r in batch.selectExpr("user_id", "cast(session_window.start as timestamp_ntz) as s", "cast(session_window.end as timestamp_ntz) as t", "n").collect())
        got = sorted((r.user_id, r.start_ts, r.end_ts, r.n) for r in registry.QUERIES["stream_session"](spark, at).collect())
        assert got == want and sum(r[3] for r in got) == e.count()


@pytest.mark.parametrize(("metric", "tau", "wide"), [("hybrid", 0.999, True), ("cosine", 0.999, False), ("cls", 0.9999, False), ("gauss", 0.999, True)])
def test_grid_loses_nothing_for_any_metric(spark, metric, tau, wide):
    v = spark.range(80).select(
        "id",
        F.array((F.col("id") % 7) * 0.004, (F.col("id") % 11) * 0.003, (F.col("id") % 3) * 0.001).alias("shape"),
        F.array(F.lit(1.0), (F.col("id") % 4) * 0.02, (F.col("id") % 9) * 0.01).alias("cls"),
    )
    brute = {(r.id_a, r.id_b) for r in similarity.brute(v, metric, least=tau).collect()}
    assert brute == {(r.id_a, r.id_b) for r in similarity.grid_pairs(v, tau, metric=metric, wide=wide).collect()} and brute
    new, index = v.where("id % 4 = 0"), v.where("id % 4 > 0")
    between = {(r.id_a, r.id_b) for r in similarity.grid_between(new, index, tau, metric=metric, wide=wide).collect()}
    assert between == {(a, b) for a, b in brute if (a % 4 == 0) != (b % 4 == 0)}


def test_a_function_of_many_blocks_takes_linear_work(spark):
    n = 100_000
    blocks = spark.range(1).select(F.lit(1).cast("long").alias("sample_id"), F.lit(0).alias("func_id"), F.lit("g").alias("grp"), F.expr(f"transform(sequence(1, {n}), i -> named_struct('n', 1L, 'a', cast(i as string), 'b', cast(i as string), 'cls', array(1L, 0L, 0L, 0L, 0L, 0L, 0L, 0L, 0L)))").alias("blocks"))
    row = flowvec.build(blocks).first()
    assert (row.n_edges, row.omega, row.zn) == (n - 1, 2 * (n - 1), 0)


def test_groups_bound_what_merges(spark):
    # 1 and 3 are linked through 2 alone, which is of another group
    pairs = spark.createDataFrame([(1, 2), (2, 3)], "id_a long, id_b long")
    members = spark.createDataFrame([(1, 1), (2, 2), (3, 3), (4, 3)], "id long, head long")
    grp = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a"), (4, "b")], "id long, grp string")
    assert dict(dedup.within_groups(pairs, members, grp).collect()) == {1: 1, 2: 2, 3: 3, 4: 2}


def test_alias_blocking_loses_nothing(spark):
    names = ["red plate", "plate red", "blue ring", "supplier 000000012", "x", "ab", "storm vault"]
    queries = [*names, "red plat", "redd plate", "supplier 000000013", "strom vault", "vault stormm", "y", "abc", "zzzz", ""]
    q, k = spark.createDataFrame([(x,) for x in queries], "query string"), spark.createDataFrame([(x,) for x in names], "canonical string")
    got = {(r.query, r.canonical) for r in alias.score(q, k).collect()}
    both = q.crossJoin(k).withColumn("s", F.greatest(alias.edit_ratio(F.col("query"), F.col("canonical")), alias.edit_ratio(alias.token_sort(F.col("query")), alias.token_sort(F.col("canonical")))))
    assert got == {(r.query, r.canonical) for r in both.where("s >= 80").collect()}


def test_nearest_lists_against_all(spark):
    v = spark.range(300).select("id", F.array(*[F.cos(F.col("id") * (k + 1)) for k in range(6)]).alias("cls"), F.expr("array()").cast("array<double>").alias("shape"))
    q = v.where("id % 50 = 0")
    true, near = ({(r.query, r.id) for r in similarity.nearest(v, q, 5, probes=p).collect()} for p in (None, 16))
    assert len(true & near) >= 0.9 * len(true)


def test_components_that_do_not_settle_fail(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(50)], "a long, b long")
    with pytest.raises(RuntimeError):
        connected_components(links, max_rounds=1)


def test_brute_force_refuses_no_number_of_vectors(spark):
    n = 2100  # over two million pairs
    v = spark.range(n).select("id", F.array(F.lit(0.0)).alias("shape"), F.array(F.cos("id"), F.sin("id"), F.cos(3 * F.col("id"))).alias("cls"))
    x = np.array([[math.cos(i), math.sin(i), math.cos(3 * i)] for i in range(n)])
    x /= np.linalg.norm(x, axis=1)[:, None]
    want = int(np.triu(x @ x.T >= 0.9999, 1).sum())
    assert similarity.brute(v, "cls", least=0.9999).count() == want > 0


def test_nearest_shuffles_no_pairs(spark, monkeypatch):
    v = spark.range(300).select("id", F.array(*[F.cos(F.col("id") * (k + 1)) for k in range(6)]).alias("cls"), F.expr("array()").cast("array<double>").alias("shape"))
    v = v.union(v.where("id % 7 = 0").select(F.col("id") + 1000, "cls", "shape"))
    q = v.where("id % 50 = 0")
    for probes in (None, 16):
        whole = similarity.nearest(v, q, 5, probes=probes)
        plan = whole._jdf.queryExecution().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan
        want = whole.collect()
        with monkeypatch.context() as m:
            m.setattr(similarity, "SOUGHT", 20)
            m.setattr(similarity, "ASKED", 3)
            assert sorted(similarity.nearest(v, q, 5, probes=probes).collect()) == sorted(want)
    # a twin is nearest
    assert {r.query: r.id for r in similarity.nearest(v, q, 5, probes=None).where("place = 1").collect()}[0] == 1000


ODD_LINES = ["", "a", "  The quick, brown fox. Jumps!! over?; ", "x\t\ty\x0bz", "\t", "Über straße 42 @home a/b É é ÉCOLE école", "12 ١٢ -- ... __ _ ʰ ǅungla", "İstanbul Kelvin ΣΊΣΥΦΟΣ, Σ", "a b c d \x1c e", "日本語のテキスト。短い,長い", "the THE De la", "😀 😀a, 😀"]


def test_block_kernel_agrees_with_the_class_expression(spark):
    lines = spark.createDataFrame([*enumerate(ODD_LINES), (-1, None)], "k int, line string")
    tokens = lines.select("k", F.explode(F.expr("filter(transform(split(line, '[.!?,;]+'), x -> trim(x)), x -> x <> '')")).alias("x"))
    tokens = tokens.selectExpr("k", "lower(substring(x, 1, 1)) as a", "lower(right(x, 1)) as b", "filter(split(x, '\\\\s+'), t -> t <> '') as t")
    plain = tokens.selectExpr("k", "a", "b", f"transform(t, t -> {class_sql('t')}) as c").collect()
    want = {}
    for r in plain:
        want.setdefault(r["k"], []).append((len(r["c"]), r["a"], r["b"], [r["c"].count(i) for i in range(1, 10)]))
    got = {r["k"]: r["blocks"] for r in _sentence_blocks(lines, "line").collect()}
    assert got.pop(-1) is None
    assert {k: [(x["n"], x["a"], x["b"], x["cls"]) for x in v] for k, v in got.items() if v} == want


@pytest.mark.parametrize("name", ["build_corpus", "release_manifest"])
def test_lines_of_documents_are_worked_once(spark, monkeypatch, name):
    built, plain = [], flowvec.build
    monkeypatch.setattr(flowvec, "build", lambda *a, **b: built.append(1) or plain(*a, **b))
    written, write = [], graph.materialize
    monkeypatch.setattr(graph, "materialize", lambda df, label: written.append(label) or write(df, label))
    registry.QUERIES[name](spark, "/root/testdata/sf0.001")
    assert len(built) == 1 and written.count("flows") == 1


def test_release_files_hold_whole_texts(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(release, "removed_at_exit", lambda *_: str(tmp_path))
    d = "/root/testdata/sf0.001"
    manifest = {(r.name, r.format): r.n_rows for r in registry.QUERIES["release_manifest"](spark, d).collect()}
    docs = spark.read.parquet(f"{d}/documents.parquet")
    whole = {tuple(r) for r in docs.collect()}
    for kind in ("parquet", "json", "csv"):
        for name in ("full", "deduplicated"):
            rows = [tuple(r) for r in release.read_file(spark, f"{tmp_path}/{name}.{kind}", kind, docs).collect()]
            assert len(rows) == manifest[name, kind] > 0 and set(rows) <= whole


ODD_VALUES = ["", None, " a ", "a\nb", "a\r\nb\r", 'say "x", \\"y\\', "\\", '"', '""', "#,;\t", "\n", "null", "\u2028\x01é😀", "a,b\n1,2,3\n"]


def test_release_keeps_odd_values_in_each_format(spark, tmp_path):
    rows = [(i, v, w) for i, (v, w) in enumerate(zip(ODD_VALUES, reversed(ODD_VALUES), strict=True))]
    df = spark.createDataFrame(rows, "id long, text string, source string")
    release.write_release(spark, str(tmp_path), {"odd": df}, {"odd": "source"})
    for kind in ("json", "csv"):
        back = release.read_file(spark, f"{tmp_path}/odd.{kind}", kind, df)
        assert [tuple(r) for r in back.orderBy("id").collect()] == rows


def test_release_notices_values_that_do_not_come_back(spark, monkeypatch, tmp_path):
    df = spark.createDataFrame([(1, "a\nb"), (2, " c ")], "id long, text string")
    monkeypatch.setitem(release.FORMATS, "csv", {"header": "true"})
    with pytest.raises(RuntimeError, match="odd.csv"):
        release.write_release(spark, str(tmp_path), {"odd": df})
