"""Exact pairs of vectors above a cosine, by dual traversal of cover trees.

Equal vectors become one point with a count. Points of unit length are dealt to the nearest of a bounded number of
pivots, the top nodes; a point also visits another node's cell if the cell's covering radius and the plane between the
two pivots leave room for a partner there, so every pair that can exist meets in exactly one cell. In a cell, points are
put into cover trees: nested levels whose radii halve, each node with the covering radius of what is below it. Two
trees are walked together, level by level; a pair of nodes goes once its distance exceeds the threshold plus both
covering radii. What reaches the last level is checked again with the cosine in double precision.

Cells yield a count of partners for each point and one link for each point that is not the smallest of its local
component; the pairs themselves stay inside the task unless they are asked for.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import connected_components, join_counted, materialize, ship
from .simhash import settle

LEVEL_RADII = (1.0, 0.5, 0.25)
SLACK = 1e-4


def level_radii(reach: float, most: int = 12) -> tuple[float, ...]:
    """Halving radii from 1 down to half the distance that is searched for."""
    out = [1.0]
    while out[-1] > reach / 2 and len(out) < most:
        out.append(out[-1] / 2)
    return tuple(out)


class CoverTree:
    """Nested levels over unit vectors: centres (indices), their covering radii, and each node's parent above."""

    def __init__(self, x: np.ndarray, radii=LEVEL_RADII):
        self.x = x
        self.levels = [(np.zeros(1, np.int64), None)]  # the root stands for all
        below = [np.zeros(len(x), np.int64)]  # of each point, its node at each level
        owner = below[0]
        for radius in radii:
            centres, parents, mine = self._net(owner, radius)
            self.levels.append((centres, parents))
            below.append(mine)
            owner = mine
        self.levels.append((np.arange(len(x)), owner))
        self.radii = []
        for (centres, _), mine in zip(self.levels[:-1], below, strict=True):
            d = np.sqrt(np.maximum(0, 2 - 2 * np.einsum("ij,ij->i", x, x[centres[mine]])))
            r = np.zeros(len(centres), x.dtype)
            np.maximum.at(r, mine, d)
            self.radii.append(r)
        self.radii.append(np.zeros(len(x), x.dtype))

    def _net(self, owner: np.ndarray, radius: float):
        """Greedy centres within each parent node, so that every point is within radius of its centre."""
        close = 1 - radius * radius / 2
        mine = np.full(len(owner), -1)
        centres: list[np.ndarray] = []
        parents: list[np.ndarray] = []
        total, left = 0, np.arange(len(owner))
        while len(left):
            head = left[:128]
            sim = self.x[head] @ self.x[head].T
            same = owner[head][:, None] == owner[head][None, :]
            near = (sim >= close) & same
            chosen: list[int] = []
            for k in range(len(head)):
                if not near[k, chosen].any():
                    chosen.append(k)
            new = head[chosen]
            sim = self.x[left] @ self.x[new].T
            sim[owner[left][:, None] != owner[new][None, :]] = -9
            best = sim.argmax(1)
            got = sim[np.arange(len(left)), best] >= close
            got[: len(head)] = True  # each is a centre or was found near one
            mine[left[got]] = total + best[got]
            mine[new] = total + np.arange(len(new))
            centres.append(new)
            parents.append(owner[new])
            total += len(new)
            left = left[~got]
        return np.concatenate(centres), np.concatenate(parents), mine


def dual(a: CoverTree, b: CoverTree, reach: float):
    """Index arrays (i, j) of points of a and b at most about `reach` apart."""
    i, j = np.zeros(1, np.int64), np.zeros(1, np.int64)
    for level in range(1, len(a.levels)):
        ca, pa_ = a.levels[level]
        cb, pb = b.levels[level]
        na, nb = np.unique(i), np.unique(j)
        rows, cols = np.flatnonzero(np.isin(pa_, na)), np.flatnonzero(np.isin(pb, nb))
        alive = np.zeros((len(a.levels[level - 1][0]), len(b.levels[level - 1][0])), bool)
        alive[i, j] = True
        d2 = 2 - 2 * (a.x[ca[rows]] @ b.x[cb[cols]].T)
        limit = reach + SLACK + a.radii[level][rows][:, None] + b.radii[level][cols][None, :]
        near = d2 <= limit * limit
        if len(na) * len(nb) > 1:
            near &= alive[pa_[rows]][:, pb[cols]]
        r, c = np.nonzero(near)
        i, j = rows[r], cols[c]
        if not len(i):
            break
    return i, j


def cell_links(vec: np.ndarray, home: np.ndarray, weight: np.ndarray, min_cos: float, block: int = 1536, within: bool = True):
    """Of one cell: counts of partners by point and links to the smallest local index.

    Pairs of two visitors are another cell's business; pairs of two home points are this one's if `within` says so.
    """
    n = len(vec)
    norm = np.sqrt((vec * vec).sum(1))
    x = (vec / norm[:, None]).astype(np.float32)
    reach = float(np.sqrt(max(0.0, 2 - 2 * min_cos)))
    order = np.argsort(~home, kind="stable")
    n_home = int(home.sum())
    radii = level_radii(reach)
    trees = [(s, CoverTree(x[order[s : min(s + block, n_home)]], radii)) for s in range(0, n_home, block)]
    links, label = np.zeros(n, np.int64), np.arange(n)

    def take(ta, tb, sa, sb):
        nonlocal label
        i, j = dual(ta, tb, reach)
        p, q = order[sa + i], order[sb + j]
        if sa == sb:
            p, q = p[i < j], q[i < j]
        for lo in range(0, len(p), 1 << 18):
            u, v = p[lo : lo + (1 << 18)], q[lo : lo + (1 << 18)]
            good = np.einsum("ij,ij->i", vec[u], vec[v]) / (norm[u] * norm[v]) >= min_cos
            u, v = u[good], v[good]
            np.add.at(links, u, weight[v])
            np.add.at(links, v, weight[u])
            label = settle(label, u, v)

    for k, (sa, ta) in enumerate(trees):
        for sb, tb in trees[k:] if within else ():
            take(ta, tb, sa, sb)
    for sb in range(n_home, n, block):
        tb = CoverTree(x[order[sb : min(sb + block, n)]], radii)
        for sa, ta in trees:
            take(ta, tb, sa, sb)
    return links, label


def near_vectors(vectors: DataFrame, min_cos: float = 0.95, id_col: str = "vec_id", vec_col: str = "embedding", pivots: int = 12, sample: int = 2000, most_in_task: int = 1 << 15, seed: int = 7) -> DataFrame:
    """One row per vector: id, n_links, component_id, kept. Pairs have a cosine of at least min_cos.

    Vectors that are null, empty, zero, or hold nulls or non-finite numbers link with nothing; so do vectors of different
    lengths with each other. Rows that repeat an id are vectors of their own. Pivots come from at most `sample` rows; they
    set where work is done, never what is found. A cell of more than `most_in_task` points is worked off in pairs of
    blocks, each in a task of its own. Components are scaled by a power of two
    first, so that very large and very small ones neither overflow nor vanish when squared. An empty table gives no rows.
    Other columns of vectors play no part, whatever their names.
    """
    ship()
    spark = vectors.sparkSession
    kind = vectors.schema[id_col].dataType.simpleString()
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    sound = F.col("v").isNotNull() & (F.size("v") > 0) & ~F.exists("v", lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf"))) & F.exists("v", lambda e: e != 0)
    power = -F.floor(F.log2(F.array_max(F.transform("v", lambda e: F.abs(e))))).cast("int")
    rows = rows.withColumn("power", F.when(sound, power)).withColumn("half", F.floor(F.col("power") / 2).cast("int"))
    # in two steps, as the power itself may be out of range; an exact product but for what is too small to matter
    scaled = lambda e: e * F.pow(F.lit(2.0), F.col("half")) * F.pow(F.lit(2.0), F.col("power") - F.col("half")) + F.lit(0.0)
    rows = materialize(rows.select("id", F.when(sound, F.transform("v", scaled)).alias("v")), "vectors")
    points = rows.where("v is not null").groupBy("v").agg(F.count("*").alias("n"), F.min("id").alias("least"), F.min(F.xxhash64("v")).alias("key"))
    points = materialize(points.withColumn("point", F.monotonically_increasing_id()), "points")
    total = points.count()
    share = min(1.0, 1.5 * sample / max(1, total))
    drawn = points.where(F.pmod(F.xxhash64("key", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).orderBy(F.xxhash64("key", F.lit(seed))).limit(sample)
    tops: dict[int, np.ndarray] = {}
    for r in drawn.select("v").collect():
        tops.setdefault(len(r["v"]), []).append(np.array(r["v"]) / np.linalg.norm(r["v"]))
    pivots = min(1024, max(pivots, int(total**0.5 / 16)))
    tops = {d: _spread_out(np.array(x), pivots) for d, x in tops.items()}
    reach = float(np.sqrt(max(0.0, 2 - 2 * min_cos))) + SLACK

    def parts(b, at):
        lists = b.column(at)
        size = np.diff(lists.offsets.to_numpy())
        flat = lists.flatten().to_numpy(zero_copy_only=False)
        start = np.cumsum(size) - size
        for d in np.unique(size).tolist():
            k = np.flatnonzero(size == d)
            yield d, k, flat[start[k][:, None] + np.arange(d)]

    def nearest(d, v):
        p = tops.get(d)
        if p is None:
            p = np.zeros((1, d))
            p[0, 0] = 1
        u = v / np.sqrt((v * v).sum(1))[:, None]
        dist = np.sqrt(np.maximum(0, 2 - 2 * u @ p.T))
        return p, dist, dist.argmin(1)

    def measure(batches):
        far: dict[tuple, float] = {}
        for b in batches:
            for d, _, v in parts(b, 0):
                _, dist, own = nearest(d, v)
                for c in np.unique(own).tolist():
                    far[d, c] = max(far.get((d, c), 0.0), float(dist[own == c, c].max()))
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in far], pa.int64()), pa.array([k[1] for k in far], pa.int64()), pa.array(list(far.values()), pa.float64())], ["d", "cell", "radius"])

    radius = {(r["d"], r["cell"]): r["radius"] for r in points.select("v").mapInArrow(measure, "d long, cell long, radius double").groupBy("d", "cell").agg(F.max("radius").alias("radius")).collect()}

    def visits(d, v):
        """Rows, their cells, and whether a cell is the row's own."""
        p, dist, own = nearest(d, v)
        covering = np.array([radius.get((d, c), -9.0) for c in range(len(p))])
        gap = np.sqrt(np.maximum(1e-12, 2 - 2 * p @ p.T))
        mine = dist[np.arange(len(v)), own]
        plane = (dist**2 - mine[:, None] ** 2) / (2 * gap[own])
        r, c = np.nonzero((plane <= reach) & (dist <= covering[None, :] + reach) & (np.arange(len(p))[None, :] > own[:, None]))
        return np.concatenate([np.arange(len(v)), r]), np.concatenate([own, c]), np.arange(len(v) + len(r)) < len(v)

    def sizes(batches):
        n: dict[tuple, int] = {}
        for b in batches:
            for d, _, v in parts(b, 0):
                _, cell, home = visits(d, v)
                for c, k in zip(*np.unique(2 * cell + home, return_counts=True), strict=True):
                    n[d, int(c)] = n.get((d, int(c)), 0) + int(k)
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in n], pa.int64()), pa.array([k[1] for k in n], pa.int64()), pa.array(list(n.values()), pa.int64())], ["d", "c", "n"])

    counted = {(r["d"], r["c"]): r["n"] for r in points.select("v").mapInArrow(sizes, "d long, c long, n long").groupBy("d", "c").agg(F.sum("n").alias("n")).collect()}
    half = max(1, most_in_task // 2)
    split = {}
    for d, c in {(d, c // 2) for d, c in counted}:
        at_home, from_afar = counted.get((d, 2 * c + 1), 0), counted.get((d, 2 * c), 0)
        split[d, c] = (1, 1) if at_home + from_afar <= most_in_task else (-(-at_home // half), -(-from_afar // half))

    def deal(batches):
        """A cell's task is (kind, i, j): 2 the whole cell; 0 home block i within itself; 1 home block i against home block j; 3 against visitors' block j."""
        for b in batches:
            ids = b.column(0).to_numpy()
            for d, k, v in parts(b, 1):
                who, cell, home = visits(d, v)
                rows: list[np.ndarray] = []
                for c in np.unique(cell).tolist():
                    s, t = split.get((d, c), (1, 1))
                    on = np.flatnonzero(cell == c)
                    put = lambda x, kind, i, j, first, c=c: rows.append(np.stack([who[x], np.full(len(x), c), np.full(len(x), kind), i + 0 * x, j + 0 * x, first + 0 * x]))
                    if (s, t) == (1, 1):
                        put(on, 2, 0, 0, home[on].astype(np.int64))
                        continue
                    own, far = on[home[on]], on[~home[on]]
                    block, theirs = ids[k[who[own]]] % max(s, 1), ids[k[who[far]]] % max(t, 1)
                    for o in range(s):
                        same, low, high = block == o, block < o, block > o
                        put(own[same], 0, o, o, 1)
                        put(own[low], 1, block[low], o, 1)
                        put(own[high], 1, o, block[high], 0)
                        put(far, 3, o, theirs, 0)
                    for o in range(t):
                        put(own, 3, block, o, 1)
                r = np.concatenate(rows, axis=1)
                for lo in range(0, r.shape[1], 8192):
                    x = r[:, lo : lo + 8192]
                    at = pa.array(k[x[0]])
                    cols = [b.column(0).take(at), b.column(2).take(at), pa.array(np.full(x.shape[1], d)), *(pa.array(x[q]) for q in range(1, 5)), pa.array(x[5] > 0), b.column(1).take(at)]
                    yield pa.RecordBatch.from_arrays(cols, ["point", "n", "d", "cell", "kind", "i", "j", "home", "v"])

    def cells(key, table):
        v = table.column("v").combine_chunks()
        d = key[0].as_py()
        vec = v.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
        point, weight = table.column("point").to_numpy(), table.column("n").to_numpy()
        order = np.argsort(point)
        links, label = cell_links(vec[order], table.column("home").to_numpy()[order], weight[order], min_cos, within=key[2].as_py() in (0, 2))
        return pa.table({"point": point[order], "links": links, "low": point[order][label]})

    dealt = points.select("point", "v", "n").mapInArrow(deal, "point long, n long, d long, cell long, kind long, i long, j long, home boolean, v array<double>")
    found = materialize(dealt.groupBy("d", "cell", "kind", "i", "j").applyInArrow(cells, "point long, links long, low long").where("links > 0"), "found")
    counts = found.groupBy("point").agg(F.sum("links").alias("links"))
    roots = connected_components(found.where("low <> point").select(F.col("point").alias("a"), F.col("low").alias("b")))
    base = points.select("point", "v", "n", "least").join(counts, "point", "left").join(roots.withColumnRenamed("node", "point"), "point", "left")
    base = base.select("v", "n", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("root", "point").alias("root"), "least")
    base = materialize(base, "points")
    low = materialize(base.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("members")), "low")
    named = materialize(join_counted(base, low, "root", "members").select("v", "n", "n_links", "component_id"), "named")
    none = rows.where("v is null").select("id", F.lit(0).cast("long").alias("n_links"), F.lit(None).cast(kind).alias("component_id"))
    out = join_counted(rows.where("v is not null"), named, "v", "n").select("id", F.col("n_links").cast("long").alias("n_links"), "component_id").unionAll(none)
    out = out.withColumn("component_id", F.coalesce("component_id", "id"))
    out = out.withColumn("kept", F.col("id").eqNullSafe(F.col("component_id"))).withColumn("component_id", F.col("component_id").cast(kind))
    return out.withColumnRenamed("id", id_col)


def _spread_out(x: np.ndarray, most: int) -> np.ndarray:
    """Up to `most` points far from each other: each next one is the farthest from those before."""
    chosen = [0]
    best = x @ x[0]
    while len(chosen) < min(most, len(x)):
        k = int(best.argmin())
        if best[k] > 1 - 1e-9:
            break
        chosen.append(k)
        best = np.maximum(best, x @ x[k])
    return x[chosen]
