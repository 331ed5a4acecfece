import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from segforest import experiments as E
from segforest import queries as Q
from segforest.functions import patches as P
from segforest.functions.geometry import lobatto
from segforest.operators import fold, forest
from segforest.plans import spheres, surface

DATA = "/root/testdata/sf0.001"
TABLES = ("lineitem", "events", "part", "embeddings", "nation", "customer", "region")


@pytest.mark.parametrize("name", ["q_culled", "q_senders", "q_partition_balance", "q_receivers_superset", "q_render_image", "q_condense_ratio", "q_balance", "q_vertices_hanging", "q_sphere_mesh", "q_hit_bilinear", "q_map_point", "q_fold_channels", "q_sql_fold", "q_window_session"])
def test_against_sql(spark, name):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    got, want = Q.QUERIES[name](spark, DATA).toPandas(), c.execute(Q.SQL[name]).df()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns) and len(got) == len(want)
    got, want = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    for k in cols:
        if got[k].dtype.kind in "ifb":
            assert np.allclose(got[k].astype(float), want[k].astype(float), atol=2e-6), k
        else:
            assert (got[k].astype(str) == want[k].astype(str)).all(), k


def test_patch_of_degree_three():
    n = np.array(lobatto(3))
    s, t = np.meshgrid(n, n, indexing="ij")
    ctrl = np.stack([2 * s - 1, 2 * t - 1, 4 + 0.3 * np.sin(3 * s) * t], -1)
    m = P.TensorMap(ctrl)
    for a, b in ((0.2, 0.7), (0.9, 0.1), (0.5, 0.5)):
        p = m.point((a, b))
        hits = P.hit_patch(ctrl, p / p[2])
        assert len(hits) == 1 and hits[0] == pytest.approx((p[2], a, b), abs=1e-8)
    lo, hi = m.box()
    pts = np.array([m.point((a, b)) for a in np.linspace(0, 1, 21) for b in np.linspace(0, 1, 21)])
    assert (pts >= lo - 1e-12).all() and (pts <= hi + 1e-12).all()
    sub = m.sub((0.25, 0.5), 0.25)
    assert sub.point((0.4, 0.8)) == pytest.approx(m.point((0.35, 0.7)))
    assert P.hit_patch(ctrl, (5.0, 0.0, 1.0)) == []


def test_two_hits_on_one_sheet():
    n = np.array(lobatto(2))
    s, t = np.meshgrid(n, n, indexing="ij")
    arch = np.stack([4 * s * (1 - s), 2 * t - 1, 3 + 2 * s], -1)  # bent so that rays with x > 0 cross it twice
    hits = P.hit_patch(arch, (0.15, 0.0, 1.0))
    exact = [x for x in np.roots([-4, 4 - 0.3, -0.45]) if 0 <= x <= 1]
    assert [h[1] for h in hits] == pytest.approx(sorted(exact))


def test_element_segments_of_a_cube():
    g = np.stack(np.meshgrid(*[[0.0, 1.0]] * 3, indexing="ij"), -1) * 2 + np.array([-1, -1, 3])
    cube = P.TensorMap(g)
    assert P.element_segments(cube, (0.05, 0.02, 1.0)) == [pytest.approx((3.0, 5.0))]
    assert P.element_segments(cube, (2.0, 0.0, 1.0)) == []
    left, right = cube.sub((0, 0, 0), 0.5), cube.sub((0, 0, 0.5), 0.5)
    a, b = P.element_segments(left, (-0.05, -0.02, 1.0)), P.element_segments(right, (-0.05, -0.02, 1.0))
    assert a[0][1] == pytest.approx(b[0][0])
    wall = P.TensorMap(np.array([[[-1, -1, 4], [-1, 1, 4]], [[1, -1, 4], [1, 1, 4]]], float))
    (alpha, cosine), = P.element_points(wall, (0.1, 0.0, 1.0))
    assert (alpha, cosine) == pytest.approx((4.0, 1 / 1.01**0.5))


def test_fractal_image_is_what_each_pixel_sees(spark):
    """Every pixel again from the mesh alone: the place in the plane, the leaf there, its corners."""
    trees, cams = surface.hexagon(spark), E._fractal_cams()
    leaves = surface.fractal_mesh(trees, 2, 4)
    got = surface.points(surface.cull(leaves, trees, cams, 4), {0: surface.opaque_grey(30), 1: surface.glowing(30)}).toPandas()
    assert not got.duplicated(["inst", "pix"]).any()
    cells = {(r.tree, r.level, r.key): r for r in leaves.collect()}
    assert sum(4.0**-level for _, level, _ in cells) == pytest.approx(2)
    want = 0
    for i in range(E._FN):
        for j in range(E._FN):
            x, y = (-0.5 + 5 * 0.8 / E._FN * (i - 23.5), 5 * 0.8 / E._FN * (j - 23.5))
            inside = any(all((q[0] - p[0]) * (y - p[1]) - (q[1] - p[1]) * (x - p[0]) > 1e-9 for p, q in zip(c, c[1:] + c[:1])) for c in ([h[1], h[2], h[4], h[3]] for h in surface.HEXAGON))
            hit = got[(got.inst == 0) & (got.i == i) & (got.j == j)]
            assert len(hit) >= inside
            want += inside
    assert want <= (got.inst == 0).sum() <= want + 4
    one = got[got.inst == 0].iloc[::37]
    for r in one.itertuples():
        c = cells[(r.tree, r.level, r.key)]
        low, high = min(c.n00, c.n10, c.n01, c.n11), max(c.n00, c.n10, c.n01, c.n11)
        assert low - 1e-9 <= r.v <= high + 1e-9 and r.b == pytest.approx(0.5 + 0.5 * r.v / 30)


def test_mesh_halves_segments_and_keeps_an_eighth_of_elements(spark):
    r = {x.stage: x for x in E.q_condense_uniform(spark, DATA).collect()}
    for k in (1, 2, 3):
        before, after = r[f"cycle_{k - 1}"], r[f"cycle_{k}"]
        assert 1.7 < before.segments / after.segments < 2.2
        assert k == 1 or before.elements == 8 * after.elements


def test_sphere_errors_fall(spark):
    r = {x.setting: x for x in E.q_sphere_errors(spark, DATA).collect()}
    order = ["gauss_c002_level7", "gauss_c002_level4", "simpson_c1_level5", "simpson_c1_level4", "simpson_one_step"]
    assert [k for k, x in sorted(r.items(), key=lambda x: x[1].rmse)] == order and r[order[0]].leaves > 50 * r[order[3]].leaves


def test_observed_orders(spark):
    want = {"euler": (1, 1), "heun2": (2, 2), "heun3": (3, 3), "rk4": (4, 4), "gauss": (4, 4), "simpson": (4, 2), "simpson_half": (4, 4)}
    for r in E.q_observed_order(spark, DATA).filter("n = 32").collect():
        assert abs(r.order - want[r.method][r.part == "b"]) < 0.6, r


def test_cloud_follows_its_law(spark):
    r = E.q_sphere_section(spark, DATA).first()
    assert abs(r.z_section) < 4 and abs(r.z_count) < 4
    assert spheres.shell_mesh(spheres.cloud(spark, 1, 0.0), 3, 0.1, 5).count() == 1


def test_channels_and_peel(spark):
    df = spark.createDataFrame([(1, 1, 0.5, 1.0, 0.0, 2.0), (1, 2, 0.8, 2.0, 0.9, 5.0)], "ray int, z int, a_r double, b_r double, a_g double, b_g double")
    r = fold.composite_channels(df, ["ray"], ["z"], ["r", "g"]).first()
    assert (r.a_r, r.b_r, r.a_g, r.b_g, r.k) == (pytest.approx(0.4), pytest.approx(2.0), 0.0, 2.0, 2)
    assert fold.composite_channels(df.limit(0), ["ray"], ["z"], ["r", "g"]).count() == 0


def test_mesh_export(spark, tmp_path):
    from segforest.sources.mesh import export_mesh

    leaves = forest.uniform(spark, 1, 2, 4).withColumn("pid", F.lit(3))
    for fmt in ("parquet", "csv", "json"):
        export_mesh(leaves, str(tmp_path / fmt), 4, fmt=fmt)
        back = spark.read.option("header", "true").option("inferSchema", "true").format(fmt).load(str(tmp_path / fmt))
        assert back.count() == 64 and back.agg(F.sum((F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0")) * (F.col("z1") - F.col("z0")))).first()[0] == pytest.approx(1)
