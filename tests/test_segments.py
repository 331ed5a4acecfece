import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from segforest import queries as Q
from segforest.functions import algebra as A
from segforest.functions import geometry as G
from segforest.operators import forest, imagetree, quadrature

DATA = "/root/testdata/sf0.001"


def one(spark, *cols):
    return spark.range(1).select(*cols).first()


def test_golden_values(spark):
    near, far = A.seg(0.5, 1.0), A.seg(0.8, 2.0)
    r = one(spark, A.seg_combine(near, far).alias("c"), A.seg_combine(far, near).alias("d"), A.seg_inverse(near).alias("i"), A.seg_inverse(A.seg_opaque(1.0)).alias("o"), A.seg_split(A.seg(0.25, 3.0), 0.5).alias("h"), A.seg_average(A.seg(0.25, 1.0), A.seg(0.25, 3.0)).alias("m"), A.seg_average(A.seg(0.25, 1.0), A.seg(0.25, 3.0), "limit").alias("l"), A.seg_const(0.0, 3.0, 2.0).alias("k"))
    assert r.c == pytest.approx((0.4, 2.0)) and r.d == pytest.approx((0.4, 2.8)) and r.i == pytest.approx((2, -2)) and r.o is None
    assert r.h == pytest.approx((0.5, 2)) and r.m == pytest.approx((0.25, 2)) and r.l == pytest.approx((0.25, 2)) and r.k == pytest.approx((1, 6))


def test_observed_orders():
    beta, gamma = (lambda x: 1 + 0.8 * np.sin(3 * x) + x), (lambda x: 2 + np.cos(5 * x) + x * x)

    def fold(method, n):
        h, a, b = 1 / n, 1.0, 0.0
        for k in range(n):  # light runs to larger x: the later piece is nearer
            p, q = quadrature.step(method, beta, gamma, k * h, h)
            a, b = p * a, p * b + q
        return np.array([a, b])

    exact = fold("rk4", 4000)
    want = {"euler": (1, 1), "heun2": (2, 2), "heun3": (3, 3), "rk4": (4, 4), "gauss": (4, 4), "simpson": (4, 2), "simpson_half": (4, 4)}
    for m, orders in want.items():
        e1, e2 = np.abs(fold(m, 16) - exact), np.abs(fold(m, 32) - exact)
        assert np.all(np.abs(np.log2(e1 / e2) - orders) < 0.6), m


def test_adaptive_error_falls_with_c():
    x = np.linspace(1, 5, 9)
    exact = np.exp(-4 * x)
    last = None
    for c in (0.5, 0.1, 0.02):
        r = quadrature.seg_eval("rk4", lambda s, p: 4 * x[s] + 0 * p, lambda s, p: 0 * p, np.zeros(9), np.ones(9), c)
        err = np.abs(r["a"] - exact).max()
        assert last is None or err < last / 50
        last = err
        assert not r["capped"].any()


def test_tiles_and_image_tree():
    assert imagetree.depth(800, 600) == 10
    assert imagetree.tile_exponent([(800, 600)], 12) == 8 and imagetree.tile_exponent([(800, 600)] * 2, 12) == 9
    a, b = imagetree.Node(0, 0, 16), imagetree.Node(0, 0, 16)
    rng, flat = np.random.default_rng(1), {}
    for k in range(12):
        x, y = rng.integers(0, 12, 2).tolist()
        rect = (x, y, x + 4, y + 3)
        lists = {(i, j): [(k, 0.5, 1.0)] for i in range(x, x + 4) for j in range(y, y + 3)}
        (a if k % 2 else b).insert(rect, lists)
        for p, s in lists.items():
            flat.setdefault(p, []).extend(s)
    a.union(b)
    got = {}
    for rect, lists in a.payloads():
        for p, s in lists.items():
            assert p not in got and rect[0] <= p[0] < rect[2] and rect[1] <= p[1] < rect[3]
            got[p] = s
    assert got == {p: sorted(s) for p, s in flat.items()}


def test_geometry():
    for r in (1, 2, 4):
        n = G.lobatto(r)
        assert n[0] == 0 and n[-1] == 1 and sum(G.lagrange(n, 0.3)) == pytest.approx(1)
    a, b, c, d = np.array([-1, -1, 4.0]), np.array([2, 0, 0.5]), np.array([0, 2, 0.3]), np.array([0.1, 0.2, 0.4])
    p = a + 0.3 * b + 0.6 * c + 0.18 * d
    assert any(abs(s - 0.3) < 1e-6 and abs(t - 0.6) < 1e-6 for _, s, t in G.hit_bilinear(a, b, c, d, p / p[2]))


def test_owners_find_all_receivers():
    o = forest.Owners([(0, 0, 0), (1, 0, 20), (2, 0, 45)])
    assert o.receivers(0, lambda level, key: True, 2) == {0, 1, 2}
    assert o.receivers(0, lambda level, key: level == 0 or key < 8, 2) == {0}


def test_ppm_round_trip(spark, tmp_path):
    from segforest.sources.ppm import PpmSource

    spark.dataSource.register(PpmSource)
    path = str(tmp_path / "i.ppm")
    rows = [(x, y, x, y, x + y) for x in range(8) for y in range(6)]
    spark.createDataFrame(rows, "x int, y int, r int, g int, b int").repartition(3).write.format("ppm").option("path", path).option("width", 8).option("height", 6).mode("append").save()
    assert sorted(map(tuple, spark.read.format("ppm").option("path", path).load().collect())) == sorted(rows)


def test_pack_round_trip(spark):
    rows = [(1, p, float(z), 0.5, 1.0) for p in (3, 5, 9) for z in range(p % 4 + 1)]
    df = spark.createDataFrame(rows, "tile int, pix long, z double, a double, b double")
    assert sorted(map(tuple, imagetree.unpack(imagetree.pack(df, ["tile"]), ["tile"]).collect())) == sorted(rows)


@pytest.mark.parametrize("name", ["q_fold_scan", "q_fold_levels", "q_classic_back_to_front", "q_overlap_resolve", "q_step_gauss", "q_complete", "q_shell_refine", "q_skybox"])
def test_against_sql(spark, name):
    c = duckdb.connect()
    for t in ("lineitem", "orders", "events", "part", "embeddings"):
        c.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    got, want = Q.QUERIES[name](spark, DATA).toPandas(), c.execute(Q.SQL[name]).df()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns) and len(got) == len(want)
    got, want = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    for k in cols:
        assert np.allclose(got[k].astype(float), want[k].astype(float), atol=2e-6), k


def test_fold_is_one_exchange(spark):
    plan = Q.QUERIES["q_fold_scan"](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1


def test_opaque_and_empty(spark):
    from segforest.operators.fold import composite

    df = spark.createDataFrame([(1, 1, 0.5, 1.0), (1, 2, 0.0, 4.0), (1, 3, 0.9, 100.0)], "ray int, z int, a double, b double")
    for how in ("scan", "array"):
        r = composite(df, ["ray"], ["z"], how).first()
        assert (r.a, r.b, r.k) == (0.0, 3.0, 3)
        assert composite(df.limit(0), ["ray"], ["z"], how).count() == 0
    assert forest.complete(spark.createDataFrame([], "tree int, level int, key long"), 4).count() == 0
