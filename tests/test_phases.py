"""The pipeline's phases, curved elements and the relational queries, against SQL and brute force."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__  # noqa: F401  registers all queries
from segforest import experiments as E
from segforest import queries as Q
from segforest.functions import patches as P
from segforest.functions.geometry import lobatto
from segforest.operators import fold, forest, imagetree, quadrature
from segforest.plans import elements, pipeline, scenes

DATA = "/root/testdata/sf0.001"
TABLES = ("region", "nation", "customer", "part", "orders", "lineitem", "events", "embeddings")
FAST = ["q_seg_general", "q_segments_given", "q_subsample", "q_effective_coeffs", "q_fold_streamable", "q_map_volume", "q_owner", "q_pair_checks", "q_imagetree_union", "q_pack_size", "q_weight_correction", "q_transfer", "q_element_segments", "q_curved_segments", "q_render_trees25", "q_surface_cosine", "q_render_pipeline", "q_adaptive_cost", "q_asof_order", "q_bucketed_headers", "q_window_sliding", "q_ray_grid", "q_rolling_inverse", "q_rolling_refold", "q_overlap_limit", "q_fold_hot_rays", "q_descend"]


@pytest.fixture(scope="module")
def tables():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", FAST)
def test_against_sql(spark, tables, name):
    got, want = Q.QUERIES[name](spark, DATA).toPandas(), tables.execute(Q.SQL[name]).df()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns) and len(got) == len(want)
    got, want = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    for k in cols:
        if got[k].dtype.kind in "ifb":
            assert np.allclose(got[k].astype(float), want[k].astype(float), atol=2e-5, equal_nan=True), k
        else:
            assert (got[k].astype(str) == want[k].astype(str)).all(), k


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_all_cycles_share_one_exchange(spark):
    seg = spark.range(10).selectExpr("id % 2 as inst", "id as pix", "id % 3 as tree", "5 as level", "id * 8 as key", "1d as z_in", "2d as z_out", "0.5d as a", "1d as b")
    for cycles in (1, 3, 5):
        assert plan(pipeline.condense(seg, 6, cycles)).count("Exchange") == 1
    df = spark.range(100).selectExpr("id % 2 as ray", "id as z", "id div 4 as fine", "id div 20 as coarse", "0.9d as a", "1d as b")
    assert plan(fold.composite(df, ["ray"], ["z"], "levels", ["coarse", "fine"])).count("Exchange") == 2


def test_stop_rules(spark):
    leaves = forest.uniform(spark, 1, 3, 5).withColumn("beta", F.lit(1.0)).withColumn("gamma", F.lit(1.0))
    cams = pipeline.front_cameras(1, 16)
    raw = forest.cut(pipeline.render(pipeline.visible_leaves(leaves, cams, 5), cams))
    level = lambda **rule: pipeline.condense(raw, 5, 5, **rule).agg(F.max("level")).first()[0]
    assert level(min_elements=2) == 0 and level(min_elements=70) == 2 and level(most_imbalance=1e9) == 0 and level(most_imbalance=0.5) == 4
    whole = pipeline.image(raw).orderBy("pix").toPandas()
    for rule in ({}, {"min_elements": 70}):
        got = pipeline.image(pipeline.condense(raw, 5, 5, **rule)).orderBy("pix").toPandas()
        assert np.allclose(got[["pix", "a", "b"]], whole[["pix", "a", "b"]])


def test_owners_of_uneven_trees(spark):
    """Leaves crowd in a corner of one tree: loads are even, and an owner's leaves lie in its own partition in curve order."""
    x = spark.range(5000).select((F.col("id") % 3 == 0).cast("int").alias("tree"), F.lit(10).alias("level"), F.when(F.col("id") % 3 == 0, F.col("id")).otherwise(F.col("id") * 100_000).alias("key"), (1 + F.col("id") % 7).alias("w"))
    got = forest.with_owner(x, "w", 16).toPandas().sort_values(["tree", "key"])
    load = got.groupby("pid").w.sum()
    assert len(load) == 16 and load.max() - load.sum() / 16 < 7 and (np.diff(got.pid) >= 0).all()
    assert forest.with_owner(x.limit(0), "w", 4).count() == 0


def test_curved_elements_against_single_rays():
    """A bent element of degree 3, each ray alone by subdivision."""
    n = np.array(lobatto(3))
    g = np.stack(np.meshgrid(n, n, n, indexing="ij"), -1)
    ctrl = np.stack([2 * g[..., 0] - 1 + 0.2 * np.sin(2 * g[..., 1]), 2 * g[..., 1] - 1, 4 + 2 * g[..., 2] + 0.3 * np.cos(2 * g[..., 0])], -1)
    cam = {"w": 12, "h": 12, "n": 1.0, "ell": 0.06, "far": 50.0}
    i, j, near, far = elements.element_rays(ctrl, cam)
    got = {(a, b): (x, y) for a, b, x, y in zip(i.tolist(), j.tolist(), near, far)}
    want = {}
    for a in range(12):
        for b in range(12):
            w = P.element_segments(P.TensorMap(ctrl), ((a - 5.5) * 0.06, (b - 5.5) * 0.06, 1.0))
            assert len(w) <= 1
            if w:
                want[a, b] = w[0]
    assert got.keys() == want.keys() and len(want) > 40
    assert all(got[k] == pytest.approx(want[k], abs=1e-6) for k in want)
    halves = [elements.element_rays(elements.restricted(ctrl, np.array([0, 0, z]), 0.5), cam) for z in (0.0, 0.5)]
    assert all(len(h[0]) for h in halves)


def test_evaluations_are_counted():
    calls = [0]

    def count(rows, x):
        calls[0] += len(x)
        return 3.0 + 0 * x

    for method in quadrature.METHODS:
        calls[0] = 0
        r = quadrature.seg_eval(method, count, count, np.zeros(5), np.linspace(0.1, 4, 5), 0.5)
        assert r["evals"].sum() == calls[0], method


def test_rolling_over_dark_and_bright_segments(spark):
    a = [0.5, 0.0, 1e-9, 2.0, 0.7, 3.0, 0.0, 0.9, 1.0, 0.2, 1e-8, 1e7]
    rows = [(1, k, x, float(k + 1)) for k, x in enumerate(a)]
    df = spark.createDataFrame(rows, "ray int, z int, a double, b double")
    for width in (1, 2, 3, 5, 20):
        for r in fold.rolling_composite(df, ["ray"], ["z"], width).collect():
            x, y = 1.0, 0.0
            for _, _, p, q in rows[max(0, r.z - width + 1) : r.z + 1]:
                x, y = x * p, x * q + y
            assert (r.roll_a, r.roll_b) == (pytest.approx(x), pytest.approx(y))
    assert fold.rolling_composite(df.limit(0), ["ray"], ["z"], 3).count() == 0


def test_overlaps_of_a_hot_ray(spark):
    rng = np.random.default_rng(0)
    z = rng.random(400) * 100
    rows = [(1, float(p), float(p + w), 0.5, 1.0) for p, w in zip(z, rng.random(400) * 5 + 0.01)] + [(2, 0.0, 1.0, 0.25, 3.0)]
    got = fold.resolve_overlaps(spark.createDataFrame(rows, "ray int, z_in double, z_out double, a double, b double"), ["ray"]).toPandas()
    ends = np.unique([e for r in rows if r[0] == 1 for e in r[1:3]])
    want = {lo: sum(r[1] < hi and r[2] > lo for r in rows if r[0] == 1) for lo, hi in zip(ends, ends[1:])}
    assert {r.z_in: r.covers for r in got[got.ray == 1].itertuples()} == {k: v for k, v in want.items() if v}
    assert len(got[got.ray == 2]) == 1


def test_escape_counts_are_those_of_the_columns(spark):
    x = spark.range(400).select((F.col("id") / 100 - 2.5).alias("re"), ((F.col("id") * 37 % 400) / 130 - 1.5).alias("im")).withColumn("n", scenes.escape_steps(F.col("re"), F.col("im"))).toPandas()
    assert (scenes.escape_counts(x.re.to_numpy(), x.im.to_numpy()) == x.n).all()


def test_trees_of_rectangles_in_groups(spark):
    rows = [(0, t, i, j, float(k), 0.5, 1.0) for k, (t, i, j) in enumerate((t, 4 * t + (k % 4), k // 4 % 4) for t in (0, 1) for k in range(10))]
    df = spark.createDataFrame(rows, "inst int, tile long, i long, j long, z double, a double, b double")
    got = imagetree.tree_images(df, ["inst", "tile"], 2).collect()
    assert sorted((r.tile, r.pixels, r.segments) for r in got) == [(0, 10, 10), (1, 10, 10)]
    again = imagetree.union_images(imagetree.tree_images(df, ["inst", "tile"], 2), imagetree.tree_images(df.filter("tile = 1"), ["inst", "tile"], 2), ["inst", "tile"], 2).collect()
    assert sorted((r.tile, r.pixels, r.segments) for r in again) == [(0, 10, 10), (1, 10, 20)]
    assert imagetree.tree_images(df.limit(0), ["inst", "tile"], 2).count() == 0


def test_image_of_a_file_uri_in_runs(spark, tmp_path):
    from segforest.sources.ppm import PpmSource, local

    spark.dataSource.register(PpmSource)
    path = f"file://{tmp_path}/i.ppm"
    rows = [(x, y, x, y, 255) for x in range(20) for y in range(10) if (x * y) % 3]
    spark.createDataFrame(rows, "x int, y int, r int, g int, b int").repartition(4).write.format("ppm").option("path", path).option("width", 20).option("height", 10).mode("append").save()
    got = {(r.x, r.y): (r.r, r.g, r.b) for r in spark.read.format("ppm").option("path", path).load().collect()}
    assert len(got) == 200 and {k for k, v in got.items() if v[2]} == {r[:2] for r in rows} and all(got[r[:2]] == r[2:] for r in rows)
    with pytest.raises(ValueError):
        local("s3://bucket/i.ppm")


def test_two_cameras_of_the_fractal():
    one, two = E._fractal_cams()
    assert one.o != two.o and one.ell != two.ell and (one.w, one.h) == (two.w, two.h)


def test_sql_fold_needs_no_python(spark):
    """A call of Python a ray took minutes on many short rays; segments of equal place fold in order of a and b."""
    assert not any(k in plan(Q.QUERIES["q_sql_fold"](spark, DATA)) for k in ("Python", "Pandas", "Arrow"))
    rows = [(1, 2.0, 0.5, 4.0), (1, 1.0, 0.8, 2.0), (1, 1.0, 0.5, 1.0), (2, 1.0, 0.0, 3.0), (2, 2.0, 0.7, 9.0)]
    x = spark.createDataFrame(rows, "ray int, z double, a double, b double")
    got = spark.sql("select ray, seg_fold(collect_list(seg_item(z, a, b))) as s from {x} group by ray order by ray", x=x).collect()
    assert [(r.s.a, r.s.b) for r in got] == [(pytest.approx(0.2), pytest.approx(3.6)), (0.0, 3.0)]


def test_packed_images_come_in_bounded_blocks(spark):
    """Blocks hold no more than they may, give all segments back, and join to the image of one piece, pixels of many segments too."""
    rows = [(size, k % 7 if k % 2 else 3, float(k * 37 % 101), 0.5, float(k)) for size in (1, 2) for k in range(200 * size)] + [(3, None, 1.0, 0.5, 1.0)]
    df = spark.createDataFrame(rows, "size int, pix long, z double, a double, b double").repartition(5)
    blocks = imagetree.pack_blocks(df, ["size"], 16).persist()
    assert blocks.agg(F.max(F.size("z"))).first()[0] == 16 and blocks.filter("continued").count() > 10
    assert sorted(imagetree.unpack(blocks, ["size"]).collect(), key=str) == sorted(df.collect(), key=str)
    whole = imagetree.pack(df, ["size"]).select("size", F.size("pix").alias("pixels"), F.size("z").alias("segments"), imagetree.packed_bytes().alias("bytes"))
    assert sorted(map(tuple, imagetree.packed_image(blocks, ["size"]).collect())) == sorted(map(tuple, whole.collect()))
    assert imagetree.packed_image(imagetree.pack_blocks(df.limit(0), ["size"]), ["size"]).count() == 0
    assert "collect_list" not in plan(Q.QUERIES["q_pack_size"](spark, DATA))


@pytest.mark.parametrize("name, table", [("q_image_nodes", "lineitem"), ("q_lagrange_unity", "orders"), ("q_observed_order", "lineitem"), ("q_ray_dir", "lineitem"), ("q_condense_uniform", None), ("q_fractal_mesh", None), ("q_fractal_image", None)])
def test_moved_onto_a_table(spark, tables, name, table):
    """Queries that once made their data up: Spark reads the table, and the rows are those of the SQL."""
    # a checkpoint hides the files; there the rows of the SQL, which reads the table, must do
    assert not table or f"{table}.parquet" in "".join(Q.QUERIES[name](spark, DATA).inputFiles())
    test_against_sql(spark, tables, name)
