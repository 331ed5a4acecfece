"""Sparse images: pixel rows, packed blocks whose size follows the segments, tiles, and a quadtree of rectangles."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def depth(w: int, h: int) -> int:
    return max(w - 1, h - 1, 0).bit_length()


def tile_exponent(sizes: list[tuple[int, int]], writers: int) -> int:
    """The least t for which all images have at most ``writers`` tiles of 2 ** t pixels' edge."""
    for t in range(64):
        if sum(-(-w // (1 << t)) * -(-h // (1 << t)) for w, h in sizes) <= writers:
            return t
        if all(1 << t >= max(w, h) for w, h in sizes):
            break
    raise ValueError("fewer writers than images")


def tile_of(pix: Column, t: int) -> Column:
    return F.shiftright(pix, 2 * t)


def pack(pixels: DataFrame, keys: list[str]) -> DataFrame:
    """Rows (keys, pix, z, a, b) as one block per key: pix of the non-empty pixels, offsets, z, a, b. Its size is
    in proportion to the segments, whatever the image's size."""
    g = pixels.groupBy(*keys, "pix").agg(F.array_sort(F.collect_list(F.struct("z", "a", "b"))).alias("s"))
    x = g.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("pix", "s"))).alias("p"))
    sizes = F.transform("p", lambda e: F.size(e["s"]))
    offsets = F.aggregate(sizes, F.array(F.lit(0)), lambda acc, n: F.concat(acc, F.array(F.element_at(acc, -1) + n)))
    flat = F.flatten(F.transform("p", lambda e: e["s"]))
    return x.select(*keys, F.col("p.pix").alias("pix"), offsets.alias("offs"), flat["z"].alias("z"), flat["a"].alias("a"), flat["b"].alias("b"))


def pack_blocks(pixels: DataFrame, keys: list[str], most: int = 1 << 16) -> DataFrame:
    """The images of ``pack`` in blocks of at most ``most`` segments, each a packed image of its own that ``unpack`` reads. Blocks
    follow the pixels; where ``continued``, a block's first pixel is also the last one of the block before. No row or task holds
    more than a block of an image: rows are dealt by ranges of pixels, sorted there (which spills), and cut as they pass."""
    import numpy as np
    import pyarrow as pa

    names = [*keys, "pix", "z", "a", "b"]
    x = pixels.select(*keys, F.col("pix").cast("long").alias("pix"), *[F.col(c).cast("double").alias(c) for c in "zab"])
    x = x.repartitionByRange(*keys, "pix").sortWithinPartitions(*names)
    kinds = {"pix": pa.list_(pa.int64()), "offs": pa.list_(pa.int32()), **{c: pa.list_(pa.float64()) for c in "zab"}, "continued": pa.bool_()}

    def changes(column):
        ids = column.dictionary_encode(null_encoding="encode").indices.to_numpy()
        return np.flatnonzero(ids[1:] != ids[:-1]) + 1

    def block(table, last):
        pix = table["pix"].combine_chunks()
        starts = np.concatenate([[0], changes(pix)])
        head = tuple(table[k][0].as_py() for k in keys)
        held = {"pix": pix.take(pa.array(starts)), "offs": np.append(starts, len(pix)), **{c: table[c].combine_chunks() for c in "zab"}}
        cols = [pa.ListArray.from_arrays([0, len(v)], pa.array(v).cast(kinds[c].value_type)) for c, v in held.items()]
        batch = pa.RecordBatch.from_arrays([*(table[k].combine_chunks()[:1] for k in keys), *cols, pa.array([last == (head, pix[0].as_py())])], names=[*keys, *kinds])
        return batch, (head, pix[-1].as_py())

    def run(batches):
        held, n, last = [], 0, None
        for b in batches:
            rows = pa.Table.from_batches([b])
            # a change of the keys ends a block
            cuts = set().union(*(changes(b.column(k)).tolist() for k in keys))
            if held and any(held[-1][k][-1].as_py() != rows[k][0].as_py() for k in keys):
                cuts.add(0)
            ends = [*sorted(cuts), b.num_rows]
            at = 0
            for end in ends:
                while at < end:
                    take = min(end - at, most - n)
                    held.append(rows.slice(at, take))
                    n, at = n + take, at + take
                    if n == most:
                        out, last = block(pa.concat_tables(held), last)
                        yield out
                        held, n = [], 0
                if n and end < b.num_rows:
                    out, last = block(pa.concat_tables(held), last)
                    yield out
                    held, n = [], 0
        if n:
            yield block(pa.concat_tables(held), last)[0]

    return x.mapInArrow(run, f"{_keys_type(x, keys)}, pix array<long>, offs array<int>, z array<double>, a array<double>, b array<double>, continued boolean")


def packed_image(blocks: DataFrame, keys: list[str]) -> DataFrame:
    """Pixels, segments and bytes of each image whose blocks (``pack_blocks``) are joined: a pixel that continues counts once, and
    the image has one closing offset."""
    again = F.col("continued").cast("long")
    size = packed_bytes() - 12 * again - 4
    return blocks.groupBy(*keys).agg(F.sum(F.size("pix") - again).alias("pixels"), F.sum(F.size("z").cast("long")).alias("segments"), (F.sum(size) + 4).alias("bytes"))


def unpack(blocks: DataFrame, keys: list[str]) -> DataFrame:
    x = blocks.select(*keys, "pix", "offs", "z", "a", "b", F.posexplode("pix").alias("i", "p"))
    ends = F.sequence(F.element_at("offs", F.col("i") + 1), F.element_at("offs", F.col("i") + 2) - 1)
    y = x.select(*keys, F.col("p").alias("pix"), "z", "a", "b", F.explode(ends).alias("k"))
    return y.select(*keys, "pix", *[F.element_at(c, F.col("k") + 1).alias(c) for c in ("z", "a", "b")])


def packed_bytes() -> Column:
    """Bytes of a packed block: 8 a pixel number, 4 an offset, 24 a segment."""
    return (F.size("pix") * 8 + F.size("offs") * 4 + F.size("z") * 24).cast("long")


def lists(df: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """``s``: the segments of each key as a list in ``order``, (order, a, b)."""
    return df.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct(*order, "a", "b"))).alias("s"))


def merge_lists(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """Sorted lists of both sides by key, merged; a key of one side alone keeps its list. Two sorted runs are what the sort
    behind array_sort merges in linear time."""
    none = F.expr("cast(array() as " + left.schema["s"].dataType.simpleString() + ")")
    j = left.join(right.withColumnRenamed("s", "_s"), keys, "full")
    return j.select(*keys, F.array_sort(F.concat(F.coalesce("s", none), F.coalesce("_s", none))).alias("s"))


def node_state(x: Column, y: Column, edge: Column, w: int, h: int) -> Column:
    """Of a node of an image's tree: wholly ``in`` the image, ``out`` of it, or to be ``split``."""
    return F.when((x >= w) | (y >= h), "out").when((x + edge <= w) & (y + edge <= h), "in").otherwise("split")


Rect = tuple[int, int, int, int]  # x0, y0, x1, y1, ends excluded


@dataclass
class Node:
    """Square (x, y, edge): empty, or one rectangle with a z-sorted list per pixel, or four children."""

    x: int
    y: int
    edge: int
    rect: Rect | None = None
    lists: dict[tuple[int, int], list] = field(default_factory=dict)
    kids: list[Node] | None = None

    def insert(self, rect: Rect, lists: dict[tuple[int, int], list]) -> None:
        """``lists`` has (z, a, b) lists by pixel inside ``rect``, which lies in this square."""
        if self.kids is None:
            if self.rect is None:
                self.rect, self.lists = rect, {p: sorted(s) for p, s in lists.items() if s}
                return
            if (both := _union(self.rect, rect)) is not None or self.edge == 1:
                self.rect = both or self.rect
                for p, s in lists.items():
                    self.lists[p] = merge_sorted(self.lists.get(p, []), sorted(s))
                return
            half, old, held = self.edge // 2, self.rect, self.lists
            self.kids = [Node(self.x + i * half, self.y + j * half, half) for j in (0, 1) for i in (0, 1)]
            self.rect, self.lists = None, {}
            self._down(old, held)
        self._down(rect, lists)

    def _down(self, rect: Rect, lists: dict) -> None:
        for k in self.kids or []:
            part = (max(rect[0], k.x), max(rect[1], k.y), min(rect[2], k.x + k.edge), min(rect[3], k.y + k.edge))
            if part[0] < part[2] and part[1] < part[3]:
                k.insert(part, {p: s for p, s in lists.items() if part[0] <= p[0] < part[2] and part[1] <= p[1] < part[3]})

    def payloads(self):
        if self.rect is not None:
            yield self.rect, self.lists
        for k in self.kids or []:
            yield from k.payloads()

    def union(self, other: Node) -> None:
        for rect, lists in list(other.payloads()):
            self.insert(rect, lists)


def _union(p: Rect, q: Rect) -> Rect | None:
    """The union of two rectangles if it is one."""
    r = (min(p[0], q[0]), min(p[1], q[1]), max(p[2], q[2]), max(p[3], q[3]))
    area = lambda s: (s[2] - s[0]) * (s[3] - s[1])
    common = max(0, min(p[2], q[2]) - max(p[0], q[0])) * max(0, min(p[3], q[3]) - max(p[1], q[1]))
    return r if area(r) == area(p) + area(q) - common else None


def merge_sorted(x: list, y: list) -> list:
    """Linear merge of two lists sorted by z."""
    import heapq

    return list(heapq.merge(x, y))


_IMAGE = "pixels long, segments long, rects array<struct<x0:int,y0:int,x1:int,y1:int>>, x array<int>, y array<int>, offs array<int>, z array<double>, a array<double>, b array<double>"


def _rows_of(tree: Node) -> dict:
    """A tree's payload as arrays: the rectangles, and the non-empty pixels with their sorted segments."""
    rects, places, offs, flat = [], [], [0], []
    for rect, held in tree.payloads():
        rects.append(dict(zip(("x0", "y0", "x1", "y1"), rect)))
        for p, s in sorted(held.items()):
            places.append(p)
            flat += s
            offs.append(len(flat))
    cols = list(zip(*flat)) or [(), (), ()]
    return {"pixels": len(places), "segments": len(flat), "rects": rects, "x": [p[0] for p in places], "y": [p[1] for p in places], "offs": offs, "z": list(cols[0]), "a": list(cols[1]), "b": list(cols[2])}


def _grown(table, keys: list[str], t: int, insert):
    """One row: the tree that ``insert`` builds from a group's rows, with the group's keys."""
    import pyarrow as pa

    rows = table.to_pylist()
    edge, tile = 1 << t, rows[0]
    found = _rows_of(insert(rows, edge))
    kinds = {"pixels": pa.int64(), "segments": pa.int64(), "rects": pa.list_(pa.struct([(k, pa.int32()) for k in ("x0", "y0", "x1", "y1")])), "x": pa.list_(pa.int32()), "y": pa.list_(pa.int32()), "offs": pa.list_(pa.int32()), "z": pa.list_(pa.float64()), "a": pa.list_(pa.float64()), "b": pa.list_(pa.float64())}
    return pa.table([table.column(k).slice(0, 1) for k in keys if k in tile] + [pa.array([found[k]], kind) for k, kind in kinds.items()], names=[*keys, *kinds])


def _keys_type(df: DataFrame, keys: list[str]) -> str:
    return ", ".join(f"{k} {df.schema[k].dataType.simpleString()}" for k in keys)


def tree_images(segments: DataFrame, keys: list[str], t: int) -> DataFrame:
    """The rectangle tree of each tile (``keys``) of 2 ** t pixels' edge from segments (keys, i, j, z, a, b): each pixel's list is
    inserted as a rectangle of one pixel. A task holds one tile's segments."""

    def insert(rows, edge):
        root = Node(rows[0]["i"] // edge * edge, rows[0]["j"] // edge * edge, edge)
        held: dict = {}
        for r in rows:
            held.setdefault((r["i"], r["j"]), []).append((r["z"], r["a"], r["b"]))
        for (x, y), s in sorted(held.items()):
            root.insert((x, y, x + 1, y + 1), {(x, y): s})
        return root

    return segments.select(*keys, "i", "j", "z", "a", "b").groupBy(*keys).applyInArrow(lambda table: _grown(table, keys, t, insert), f"{_keys_type(segments, keys)}, {_IMAGE}")


def union_images(left: DataFrame, right: DataFrame, keys: list[str], t: int) -> DataFrame:
    """Both sides' trees of each tile as one, pixel lists merged; a tile of one side alone stays as it is."""

    def insert(rows, edge):
        root = None
        for r in rows:
            node = Node(r["x"][0] // edge * edge, r["y"][0] // edge * edge, edge)
            held = {p: list(zip(*(r[c][lo:hi] for c in "zab"))) for p, lo, hi in zip(zip(r["x"], r["y"]), r["offs"], r["offs"][1:])}
            for rect in (tuple(q[k] for k in ("x0", "y0", "x1", "y1")) for q in r["rects"]):
                node.insert(rect, {p: s for p, s in held.items() if rect[0] <= p[0] < rect[2] and rect[1] <= p[1] < rect[3]})
            if root is None:
                root = node
            else:
                root.union(node)
        return root

    return left.unionByName(right).groupBy(*keys).applyInArrow(lambda table: _grown(table, keys, t, insert), f"{_keys_type(left, keys)}, {_IMAGE}")
