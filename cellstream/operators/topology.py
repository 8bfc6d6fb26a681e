"""Rebuilding a mesh from decoded points: structured grids by joins, planar Delaunay triangulation by incremental insertion."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def grid_triangles(points: DataFrame, i: str = "i", j: str = "j", vid: str = "v") -> DataFrame:
    """(v0, v1, v2): the two triangles on either side of a grid square's diagonal, each where its own three corners are there."""
    p = points.select(F.col(i).alias("i"), F.col(j).alias("j"), F.col(vid).alias("v"))

    def corner(di, dj, name):
        return p.select((F.col("i") - di).alias("i"), (F.col("j") - dj).alias("j"), F.col("v").alias(name))

    diagonal = p.join(corner(1, 1, "x"), ["i", "j"])
    right, up = diagonal.join(corner(1, 0, "r"), ["i", "j"]), diagonal.join(corner(0, 1, "u"), ["i", "j"])
    return right.select(F.col("v").alias("v0"), F.col("r").alias("v1"), F.col("x").alias("v2")).unionByName(up.select(F.col("v").alias("v0"), F.col("x").alias("v1"), F.col("u").alias("v2")))


def _side(a, b, c) -> int:
    return (b[0] - a[0]) * (c[1] - a[1]) - (b[1] - a[1]) * (c[0] - a[0])


def in_circle(a, b, c, p) -> bool:
    """Exact: p inside the circle of the counter-clockwise triangle a, b, c (whole numbers).

    Points on the circle are settled as if each point were lifted a little, the smallest by (x, y) by far the most: any two
    triangulations of sets that share such points settle them alike.
    """
    (ax, ay), (bx, by), (cx, cy) = ((q[0] - p[0], q[1] - p[1]) for q in (a, b, c))
    sa, sb, sc = ax * ax + ay * ay, bx * bx + by * by, cx * cx + cy * cy
    of_a, of_b, of_c = bx * cy - by * cx, cx * ay - cy * ax, ax * by - ay * bx
    value = sa * of_a + sb * of_b + sc * of_c
    if value:
        return value > 0
    first = min(a, b, c, p)
    return first != p and {a: of_a, b: of_b, c: of_c}[first] > 0


def delaunay(points: list[tuple[int, int]], ordered: bool = True) -> tuple[list[tuple[int, int, int]], int]:
    """Triangles (indices, counter-clockwise) and walking steps; points distinct. With ``ordered`` each insertion starts
    from the last triangle, so an insertion order of near neighbours keeps the walk short."""
    n = len(points)
    if n < 3:
        return [], 0
    reach = 4 * (1 + max(max(abs(x), abs(y)) for x, y in points)) ** 2 * 8
    pts = [*points, (-3 * reach, -reach), (3 * reach, -reach), (0, 3 * reach)]
    tri: dict[int, tuple[int, int, int]] = {0: (n, n + 1, n + 2)}
    edge = {(n, n + 1): 0, (n + 1, n + 2): 0, (n + 2, n): 0}
    serial, last, steps = 1, 0, 0
    for k in range(n):
        at = last if ordered else next(iter(tri))
        while True:  # walk across the edge that the point lies beyond
            steps += 1
            a, b, c = tri[at]
            for u, v in ((a, b), (b, c), (c, a)):
                if _side(pts[u], pts[v], pts[k]) < 0:
                    at = edge[v, u]
                    break
            else:
                break
        bad, queue = {at}, [at]
        while queue:
            a, b, c = tri[queue.pop()]
            for u, v in ((a, b), (b, c), (c, a)):
                t = edge.get((v, u))
                if t is not None and t not in bad and in_circle(*(pts[w] for w in tri[t]), pts[k]):
                    bad.add(t)
                    queue.append(t)
        border = []
        for t in bad:
            a, b, c = tri[t]
            border += [(u, v) for u, v in ((a, b), (b, c), (c, a)) if edge.get((v, u)) not in bad]
        for t in bad:
            a, b, c = tri.pop(t)
            for e in ((a, b), (b, c), (c, a)):
                edge.pop(e, None)
        for u, v in border:
            if _side(pts[u], pts[v], pts[k]) == 0:
                continue
            tri[serial] = (u, v, k)
            edge[u, v] = edge[v, k] = edge[k, u] = serial
            last, serial = serial, serial + 1
    return [t for t in tri.values() if max(t) < n], steps


def _circle(a, b, c):
    """Twice-area and centre times it, so that the centre is exact: (d, x, y) with centre (x / d, y / d), d > 0."""
    d = 2 * _side(a, b, c)
    sa, sb, sc = (q[0] * q[0] + q[1] * q[1] for q in (a, b, c))
    x = sa * (b[1] - c[1]) + sb * (c[1] - a[1]) + sc * (a[1] - b[1])
    y = sa * (c[0] - b[0]) + sb * (a[0] - c[0]) + sc * (b[0] - a[0])
    return (d, x, y) if d > 0 else (-d, -x, -y)


def _certain(points, box, reach, world):
    """Triangles of the points within ``reach`` of a tile whose circle has its centre in the tile and lies within the points'
    box, or that box holds the world: they are triangles of the whole set. Boxes are half-open (x0, y0, x1, y1)."""
    x0, y0, x1, y1 = box
    whole = x0 - reach <= world[0] and y0 - reach <= world[1] and x1 + reach >= world[2] and y1 + reach >= world[3]
    for t in delaunay(points)[0]:
        corners = [points[k] for k in t]
        d, x, y = _circle(*corners)
        if not (x0 * d <= x < x1 * d and y0 * d <= y < y1 * d):
            continue
        r = ((x - corners[0][0] * d) ** 2 + (y - corners[0][1] * d) ** 2) ** 0.5 * (1 + 1e-9)
        if whole or (x - r >= (x0 - reach) * d and x + r < (x1 + reach) * d and y - r >= (y0 - reach) * d and y + r < (y1 + reach) * d):
            yield corners


def _between(points, border):
    """Triangles of ``points`` that are reached from the outer sides of the directed ``border`` edges, or from points on none,
    without crossing a border edge; all triangles if there is no border."""
    pts = sorted(points)
    triangles = [tuple(pts[k] for k in t) for t in delaunay(pts)[0]]
    if not border:
        return triangles
    of = {e: t for t in triangles for e in ((t[0], t[1]), (t[1], t[2]), (t[2], t[0]))}
    walls = {frozenset(e) for e in border}
    bound = {p for e in border for p in e}
    seen = {of[v, u] for u, v in border if (v, u) in of} | {t for t in triangles if not bound.issuperset(t)}
    queue = list(seen)
    while queue:
        t = queue.pop()
        for u, v in ((t[0], t[1]), (t[1], t[2]), (t[2], t[0])):
            near = of.get((v, u))
            if near is not None and near not in seen and frozenset((u, v)) not in walls:
                seen.add(near)
                queue.append(near)
    return list(seen)


CORNERS = "x0 long, y0 long, x1 long, y1 long, x2 long, y2 long"


def delaunay_tiles(points: DataFrame, side: int, x: str = "a0", y: str = "a1", halo: int | None = None) -> DataFrame:
    """(x0, y0, x1, y1, x2, y2): the Delaunay triangulation of all points, corners counter-clockwise from the smallest.

    Square tiles of ``side`` with the points within a halo give the triangles that are certain to be those of the whole set. What they
    leave open, along the hull and around empty regions, has its corners on the open edges: those points alone are triangulated
    in one task, and the triangles between the open edges complete the set.
    """
    from ..sources.shared import written

    pts = written(points.select(F.col(x).cast("long").alias("x"), F.col(y).cast("long").alias("y")).distinct(), "vertices")
    b = pts.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    if b[0] is None:
        return pts.sparkSession.createDataFrame([], CORNERS)
    world, reach = (b[0], b[1], b[2] + 1, b[3] + 1), 2 * side if halo is None else halo
    spots = lambda c, lo, hi: F.sequence(F.greatest(F.lit(lo // side), F.floor((F.col(c) - reach) / side)), F.least(F.lit(hi // side), F.floor((F.col(c) + reach) / side)))
    held = pts.select("x", "y", F.explode(spots("x", world[0], world[2] - 1)).alias("tx")).select("*", F.explode(spots("y", world[1], world[3] - 1)).alias("ty"))
    certain = written(held.groupBy("tx", "ty").applyInPandas(_tile_builder(side, reach, world), CORNERS), "triangles")
    ends = F.explode(F.array(*[F.struct(F.col(f"x{i}").alias("ux"), F.col(f"y{i}").alias("uy"), F.col(f"x{j}").alias("vx"), F.col(f"y{j}").alias("vy")) for i, j in ((0, 1), (1, 2), (2, 0))])).alias("e")
    edges = written(certain.select(ends).select("e.*"), "edges")
    back = edges.select(F.col("vx").alias("ux"), F.col("vy").alias("uy"), F.col("ux").alias("vx"), F.col("uy").alias("vy"))
    open_ = edges.join(back, ["ux", "uy", "vx", "vy"], "left_anti")
    lonely = pts.join(edges.select(F.col("ux").alias("x"), F.col("uy").alias("y")), ["x", "y"], "left_anti").select(F.col("x").alias("ux"), F.col("y").alias("uy"), F.lit(None).cast("long").alias("vx"), F.lit(None).cast("long").alias("vy"))
    seam = open_.unionByName(lonely).groupBy(F.lit(0).alias("one")).applyInPandas(_seam_builder, CORNERS)
    return certain.unionByName(seam)


def _rows(triangles):
    """Corners from the smallest, counter-clockwise, as a frame."""
    import pandas as pd

    rows = []
    for t in triangles:
        k = min(range(3), key=lambda i: t[i])
        rows.append([v for p in (*t[k:], *t[:k]) for v in p])
    return pd.DataFrame(rows, columns=["x0", "y0", "x1", "y1", "x2", "y2"], dtype="int64")


def _tile_builder(side: int, reach: int, world):
    def build(pdf):
        tx, ty = int(pdf["tx"].iloc[0]), int(pdf["ty"].iloc[0])
        pts = sorted({(int(a), int(b)) for a, b in zip(pdf["x"], pdf["y"], strict=True)})
        return _rows(_certain(pts, (tx * side, ty * side, (tx + 1) * side, (ty + 1) * side), reach, world))

    return build


def _seam_builder(pdf):
    border = [((int(r.ux), int(r.uy)), (int(r.vx), int(r.vy))) for r in pdf.dropna().itertuples()]
    points = {(int(a), int(b)) for a, b in zip(pdf["ux"], pdf["uy"], strict=True)} | {p for e in border for p in e}
    return _rows(_between(points, border))
