"""Clouds of spheres: placement by a size law, meshes refined at their shells, and rays through the elements with a
sharp but smooth step of density at each shell, integrated by any rule and threshold."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sfc import coordinate, morton2
from ..operators import forest, quadrature
from .scenes import expected_section, poisson, section, shell_meets_box, uniform01


def cloud(spark: SparkSession, level: int, coverage: float, s0: float = 1e-3, s1: float = 1e-1) -> DataFrame:
    """Spheres (sid, cx, cy, cz, r) in the unit cube: each element of a uniform mesh has a Poisson number of them with
    mean ``coverage`` x its face over the expected section, centres even in the element, sections by the law 1/s."""
    n = 1 << (3 * level)
    mean = coverage * 4.0**-level / expected_section(s0, s1)
    most = int(mean + 12 * mean**0.5 + 16)
    x = spark.range(n).select(F.col("id").alias("cell"), poisson(uniform01(F.col("id"), 7), mean, most).alias("c")).filter("c > 0")
    x = x.withColumn("k", F.explode(F.sequence(F.lit(1), F.col("c")))).withColumn("sid", F.col("cell") * (most + 1) + F.col("k"))
    at = [(coordinate(F.col("cell"), a, level) + uniform01(F.col("sid"), a + 1)) / float(1 << level) for a in range(3)]
    return x.select("sid", *[c.alias(f"c{n_}") for c, n_ in zip(at, "xyz")], F.sqrt(section(uniform01(F.col("sid"), 4), s0, s1) / F.pi()).alias("r"))


def _node_box(level: str = "level", p: str = "p", top: int = 20):
    edge = F.expr(f"power(2.0D, -{level})")
    lo = [coordinate(F.col(p), a, top) * edge for a in range(3)]
    return lo, [c + edge for c in lo], edge


def _pairs(spheres: DataFrame, depth: int, go) -> list[DataFrame]:
    """Pairs (level, p, sphere) by level, top-down: a node's sphere is tried on its eight children only. ``go`` (lo, hi,
    edge) says which pairs live. No exchange."""
    x = spheres.select("sid", "cx", "cy", "cz", "r", F.lit(0).alias("level"), F.lit(0).cast("long").alias("p"))
    out = []
    for level in range(depth + 1):
        if level:
            x = x.withColumn("c", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long")))).withColumn("p", F.shiftleft("p", 3) + F.col("c")).withColumn("level", F.lit(level)).drop("c")
        x = x.filter(go(*_node_box(top=max(level, 1))))
        out.append(x)
    return out


def pair_checks(spheres: DataFrame, depth: int, eps: float) -> DataFrame:
    """By level: pairs of a sphere and a node that the descent checks, those that meet (what any search must find), and all pairs."""
    ball = _ball(eps)
    total, out = spheres.agg(F.count("*").alias("n")), None
    levels = _pairs(spheres, depth, ball)
    for level, x in enumerate(levels):
        found = x.agg(F.count("*").alias("needed"))
        checked = total.select(F.col("n").alias("checked")) if level == 0 else levels[level - 1].agg((F.count("*") * 8).alias("checked"))
        row = found.join(checked).join(total).select(F.lit(level).alias("level"), "checked", "needed", (F.col("n") * (1 << (3 * level))).alias("all_pairs"))
        out = row if out is None else out.unionByName(row)
    return out


def _ball(eps: float):
    """Whether the ball of radius (1 + eps) r meets a box."""
    return lambda lo, hi, edge: sum((F.pow(F.greatest(a - F.col(f"c{n}"), F.col(f"c{n}") - b, F.lit(0.0)), 2) for n, a, b in zip("xyz", lo, hi)), F.lit(0.0)) <= F.pow(F.col("r") * (1 + eps), 2)


def shell_mesh(spheres: DataFrame, level: int, eps: float, top: int) -> DataFrame:
    """Leaves (tree, level, key): a node is refined while it meets the shell of a sphere between (1 - eps) r and
    (1 + eps) r and its edge is at least eps r / 2, down to ``level``; complete, not balanced."""
    c, r = [F.col("cx"), F.col("cy"), F.col("cz")], F.col("r")
    go = lambda lo, hi, edge: shell_meets_box(c, r, lo, hi, eps) & (edge >= r * (eps / 2))
    split = None
    for x in _pairs(spheres, level - 1, go) if level else []:
        x = x.select("level", "p").distinct()
        split = x if split is None else split.unionByName(x)
    root = spheres.sparkSession.range(1).select(F.lit(0).alias("level"), F.lit(0).cast("long").alias("p"))
    if split is None:
        return root.select(F.lit(0).alias("tree"), "level", F.col("p").alias("key"))
    split = forest.cut(split)
    kids = split.select((F.col("level") + 1).alias("level"), F.explode(F.expr("transform(sequence(0, 7), c -> shiftleft(p, 3) + c)")).alias("p"))
    leaves = kids.unionByName(root).join(split, ["level", "p"], "left_anti")
    return leaves.select(F.lit(0).alias("tree"), "level", F.call_function("shiftleft", F.col("p"), F.expr(f"cast(3 * ({top} - level) as int)")).alias("key"))


def spheres_of_leaves(leaves: DataFrame, spheres: DataFrame, eps: float, top: int) -> DataFrame:
    """Leaves with ``near``: the spheres whose ball of radius (1 + eps) r meets them, as an array; leaves without one
    have an empty array. Candidate pairs descend from the root and meet leaves by an equi join."""
    deepest = leaves.agg(F.max("level")).first()[0] or 0
    ball = _ball(eps)
    pairs = None
    for x in _pairs(spheres, deepest, ball):
        pairs = x if pairs is None else pairs.unionByName(x)
    shift = F.expr(f"cast(3 * ({top} - level) as int)")
    own = leaves.select("tree", F.col("level").cast("int").alias("level"), "key", F.call_function("shiftright", F.col("key"), shift).alias("p"))
    near = own.join(pairs, ["level", "p"]).groupBy("tree", "level", "key").agg(F.array_sort(F.collect_list(F.struct("sid", "cx", "cy", "cz", "r"))).alias("near"))
    j = own.drop("p").join(near, ["tree", "level", "key"], "left")
    return j.withColumn("near", F.coalesce("near", F.expr("cast(array() as array<struct<sid:bigint,cx:double,cy:double,cz:double,r:double>>)")))


#: Rays that a task integrates at once.
RAYS = 1 << 17


def _cast(cam: dict, box: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, ...]:
    """Directions [3, rays] of pixels (i, j), and the ray parameters at which they enter and leave their boxes [6, rays], within the clipping planes.
    ``cam`` has the cameras' numbers by ray."""
    p, q = (i - (cam["w"] - 1) / 2) * cam["ell"], (j - (cam["h"] - 1) / 2) * cam["ell"]
    d = cam["v"] + p * cam["t"] + q * cam["u"]
    with np.errstate(divide="ignore", invalid="ignore"):
        t0, t1 = (box[:3] - cam["o"]) / d, (box[3:] - cam["o"]) / d
    flat, inside = np.abs(d) < 1e-12, (cam["o"] >= box[:3]) & (cam["o"] < box[3:])
    near = np.where(flat, np.where(inside, -np.inf, np.inf), np.minimum(t0, t1)).max(0)
    far = np.where(flat, np.where(inside, np.inf, -np.inf), np.maximum(t0, t1)).min(0)
    return d, np.maximum(near, 1.0), np.minimum(far, cam["end"])


def render(visible: DataFrame, cams: list, method: str, c: float, eps: float, dense: float = 8.0, glow: float = 4.0, max_depth: int = 16) -> DataFrame:
    """Segments of all rays through visible leaves (with ``near``, box x0..z1, pixel rectangle): inst, i, j, pix, z_in, z_out, a,
    b, evals, tree, level, key. Density is ``dense`` inside each sphere and falls to 0 between (1 - eps) r and (1 + eps) r;
    light is ``glow`` times the density. Leaves far from all spheres give identity segments and are left out.
    ``c`` 0 takes one step an element, without recursion. A leaf is one row, spheres and all; its rays are made in the task."""
    import pyarrow as pa

    number = {cam.inst: k for k, cam in enumerate(cams)}
    table = {n: np.array([getattr(cam, n) for cam in cams], float).T for n in ("o", "v", "t", "u", "w", "h", "ell")} | {"end": np.array([cam.far / cam.n for cam in cams])}
    x = visible.filter(F.size("near") > 0).select("inst", "i0", "i1", "j0", "j1", *[f"{k}{side}" for side in (0, 1) for k in "xyz"], "near", "tree", F.col("level").cast("int").alias("level"), "key")

    def some(t, get, first, counts, ball, lo, hi, rays):
        """Segments of the rays of the leaves lo to hi of a batch."""
        leaf = np.repeat(np.arange(lo, hi), rays[lo:hi])
        k = np.arange(len(leaf)) - np.repeat(np.cumsum(rays[lo:hi]) - rays[lo:hi], rays[lo:hi])
        wide = (get["i1"] - get["i0"] + 1)[leaf]
        i, j = get["i0"][leaf] + k % wide, get["j0"][leaf] + k // wide
        box = np.stack([get[f"{n}{side}"] for side in (0, 1) for n in "xyz"])[:, leaf]
        cam = {n: v[..., get["cam"][leaf]] for n, v in table.items()}
        d, z_in, z_out = _cast(cam, box, i, j)
        keep = np.flatnonzero(z_in < z_out)
        leaf, i, j, d, o, z_in, z_out = leaf[keep], i[keep], j[keep], d[:, keep], cam["o"][:, keep], z_in[keep], z_out[keep]
        speed, many, start = np.sqrt((d * d).sum(0)), counts[leaf], first[leaf]

        def density(s, x):  # x: length from the far end, growing towards the eye
            at = o[:, s] + d[:, s] * (-x / speed[s])
            rho = np.zeros(len(s))
            for n in range(int(many[s].max()) if len(s) else 0):
                m = many[s] > n
                b = ball[:, start[s[m]] + n]
                q = np.sqrt(((at[:, m] - b[:3]) ** 2).sum(0)) / b[3]
                u = np.clip((1 + eps - q) / (2 * eps), 0, 1)
                rho[m] += u * u * (3 - 2 * u)
            return dense * rho

        r = quadrature.seg_eval(method, density, lambda s, x: glow * density(s, x), -z_out * speed, -z_in * speed, c or np.inf, max_depth)
        same = {n: t.column(t.schema.get_field_index(n)).take(pa.array(leaf)) for n in ("inst", "tree", "level", "key")}
        return pa.RecordBatch.from_arrays([same["inst"], pa.array(i), pa.array(j), pa.array(z_in), pa.array(z_out), *(pa.array(r[n]) for n in ("a", "b", "evals")), same["tree"], same["level"], same["key"]], names=["inst", "i", "j", "z_in", "z_out", "a", "b", "evals", "tree", "level", "key"])

    def run(batches):
        for t in batches:
            get = {n: t.column(k).to_numpy(zero_copy_only=False) for k, n in enumerate(t.schema.names) if n not in ("near", "inst")}
            get["cam"] = np.array([number[v] for v in t.column(0).to_pylist()], np.int64)
            lists = t.column(t.schema.get_field_index("near"))
            counts = np.asarray(lists.value_lengths()).astype(np.int64)
            flat = lists.flatten()
            ball = np.stack([np.asarray(flat.field(k)) for k in (1, 2, 3, 4)])
            rays = (get["i1"] - get["i0"] + 1) * (get["j1"] - get["j0"] + 1)
            total, lo = np.cumsum(rays), 0
            while lo < t.num_rows:
                hi = max(lo + 1, int(np.searchsorted(total, (total[lo - 1] if lo else 0) + RAYS, "right")))
                yield some(t, get, np.cumsum(counts) - counts, counts, ball, lo, hi, rays)
                lo = hi

    out = x.mapInArrow(run, "inst int, i long, j long, z_in double, z_out double, a double, b double, evals long, tree int, level int, key long")
    return out.withColumn("pix", morton2(F.col("i"), F.col("j")))
