"""Weighted k-way partitions: curve split, coordinate bisection, multilevel, refinement, and baselines.

A partition is a table (v, k). All methods are deterministic; ties go by vertex id or its hash.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import store

#: The multilevel method splits on the driver once the graph has at most this many vertices.
COARSE = 2_000
#: While the graph is this many times larger, one vertex in so many is a centre that draws its neighbours.
CENTRES = 8
#: Tables of vertices with at most this many rows go to every task; larger ones are joined by shuffle.
SPREAD = 2_000_000


def partition_hash(vertex: DataFrame, n_dom: int) -> DataFrame:
    """Baseline: scattered by a multiplicative rule of the id."""
    return vertex.select("v", ((F.col("v") % 1_000_003 * 7_919 + 12_345) % 1_000_003 % n_dom).cast("int").alias("k"))


def partition_block(vertex: DataFrame, n_dom: int) -> DataFrame:
    """Baseline: equal contiguous runs of ids, over all meshes together."""
    ranked = prefix_sums(vertex.select("v", F.lit(1.0).alias("w")), F.col("v").cast("double"))
    total = vertex.count()
    return ranked.select("v", F.least(F.lit(n_dom - 1), F.floor((F.col("before")) * n_dom / total)).cast("int").alias("k"))


def partition_octant(vertex: DataFrame, cuts: tuple[int, ...] = (2, 2, 2), lo: float = 0.0, hi: float = 1.0) -> DataFrame:
    """Equal boxes by coordinate, cuts[a] along axis a."""
    k, stride = F.lit(0), 1
    for a, n in enumerate(cuts):
        at = F.greatest(F.lit(0), F.least(F.lit(n - 1), F.floor((F.col("x")[a] - lo) / ((hi - lo) / n) + 1e-12)))
        k, stride = k + at * stride, stride * n
    return vertex.select("v", k.cast("int").alias("k"))


def partition_from_table(df: DataFrame, v: str = "v", k: str = "k") -> DataFrame:
    """A partition computed elsewhere."""
    return df.select(F.col(v).cast("long").alias("v"), F.col(k).cast("int").alias("k"))


def partition_per_mesh(parts: list[DataFrame]) -> DataFrame:
    """Baseline: partitions of single meshes side by side, made without the edges between the meshes."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def prefix_sums(df: DataFrame, key: Column, w: str = "w", buckets: int | None = None) -> DataFrame:
    """Adds ``before``: the sum of weights that precede a row in the order (key, v).

    Rows are cut into buckets at quantiles of the key; sums of buckets are offsets, and a window
    runs inside a bucket only, so no task holds more than about a bucket. The driver sees the bucket bounds alone.
    """
    keyed = df.withColumn("__key", key)
    n = buckets or max(1, min(4096, df.count() // 20_000))
    bounds = [] if n == 1 else sorted(set(keyed.approxQuantile("__key", [i / n for i in range(1, n)], 0.1 / n)))
    at = F.lit(0) if not bounds else F.size(F.filter(F.array(*[F.lit(float(b)) for b in bounds]), lambda b: b <= F.col("__key")))
    keyed = keyed.withColumn("__b", at)
    sums = keyed.groupBy("__b").agg(F.sum(w).alias("s"))
    offset = sums.withColumn("off", F.coalesce(F.sum("s").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).drop("s")
    inside = Window.partitionBy("__b").orderBy("__key", "v").rowsBetween(Window.unboundedPreceding, -1)
    return keyed.join(F.broadcast(offset), "__b").withColumn("before", F.col("off") + F.coalesce(F.sum(w).over(inside), F.lit(0.0))).drop("__b", "__key", "off")


def morton_key(x: Column, lo: list[float], hi: list[float], bits: int = 10) -> Column:
    """Interleaved bits of the coordinates' cells; ``bits`` per axis, 2^bits cells."""
    dim = len(lo)
    key = F.lit(0).cast("long")
    for a in range(dim):
        cell = F.greatest(F.lit(0), F.least(F.lit((1 << bits) - 1), F.floor((x[a] - lo[a]) / (hi[a] - lo[a]) * (1 << bits)))).cast("long")
        for b in range(bits):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(cell, b).bitwiseAND(F.lit(1)), b * dim + a))
    return key


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """Index along the Hilbert curve of integer cells (rows), by transposing axes bit by bit."""
    x = cells.astype(np.int64).T.copy()
    dim = len(x)
    m = 1 << (bits - 1)
    q = m
    while q > 1:
        p = q - 1
        for i in range(dim):
            on = (x[i] & q) != 0
            t = (x[0] ^ x[i]) & p
            x[0] = np.where(on, x[0] ^ p, x[0] ^ t)
            if i:
                x[i] = np.where(on, x[i], x[i] ^ t)
        q >>= 1
    for i in range(1, dim):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = m
    while q > 1:
        t = np.where((x[dim - 1] & q) != 0, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dim):
            out = (out << 1) | ((x[i] >> b) & 1)
    return out


def _split(ordered: DataFrame, n_dom: int) -> DataFrame:
    total = ordered.agg(F.sum("w")).first()[0] or 1.0
    return ordered.select("v", F.least(F.lit(n_dom - 1), F.floor((F.col("before") + F.col("w") / 2) * n_dom / total)).cast("int").alias("k"))


def partition_curve(vertex: DataFrame, weight: DataFrame, n_dom: int, lo: list[float], hi: list[float], curve: str = "morton", bits: int = 10) -> DataFrame:
    """Runs of equal weight along a space-filling curve through the vertices."""
    df = vertex.select("v", "x").join(weight, "v")
    if curve == "hilbert":
        @F.pandas_udf("long")
        def key(x):
            import pandas as pd

            at = np.array(x.tolist(), float).reshape(len(x), -1)
            cells = np.clip(np.floor((at - lo) / (np.array(hi) - lo) * (1 << bits)), 0, (1 << bits) - 1)
            return pd.Series(hilbert_index(cells, bits))

        order = key("x")
    else:
        order = morton_key(F.col("x"), lo, hi, bits)
    return _split(prefix_sums(store(df.withColumn("__o", order), "curve"), F.col("__o").cast("double")), n_dom)


def partition_rcb(vertex: DataFrame, weight: DataFrame, n_dom: int, passes: int = 3, bins: int = 256) -> DataFrame:
    """Recursive coordinate bisection: each box is cut across its longest axis at the weighted share.

    The cut is found by ``passes`` histograms of ``bins`` bins, each refining one bin of the last, so
    no box is ever sorted or held by one task. Equal coordinates are told apart by the other axes.
    """
    df = store(vertex.select("v", "x").join(weight, "v").withColumn("box", F.lit(0)), "rcb")
    dim = len(vertex.select("x").first()[0])
    todo = {0: (0, n_dom)}  # box -> (first part, number of parts)
    final: dict[int, int] = {}
    while todo:
        for b, (first, n) in list(todo.items()):
            if n == 1:
                final[b] = first
                del todo[b]
        if not todo:
            break
        ext = df.where(F.col("box").isin(list(todo))).groupBy("box").agg(*[f(F.col("x")[a]).alias(f"{m}{a}") for a in range(dim) for f, m in ((F.min, "lo"), (F.max, "hi"))]).collect()
        plan = {}
        for r in ext:
            size = [r[f"hi{a}"] - r[f"lo{a}"] for a in range(dim)]
            axes = sorted(range(dim), key=lambda a: (-size[a], a))
            plan[r["box"]] = ([(a, r[f"lo{a}"], size[a]) for a in axes], todo[r["box"]])

        def key_of(p) -> Column:
            out, scale = F.lit(0.0), 1.0
            for a, lo, size in p:
                if size > 0:
                    out = out + (F.col("x")[a] - lo) / size * scale
                scale *= 1e-4
            return out

        key = F.lit(0.0)
        for b, (axes, _) in plan.items():
            key = F.when(F.col("box") == b, key_of(axes)).otherwise(key)
        df = store(df.withColumn("key", key), "rcb")
        low = {b: 0.0 for b in plan}
        width = {b: 1.001 for b in plan}
        under = {b: 0.0 for b in plan}
        goal = {}
        for step in range(passes):
            lo_c = F.element_at(F.create_map(*[F.lit(z) for b in plan for z in (b, low[b])]), F.col("box"))
            w_c = F.element_at(F.create_map(*[F.lit(z) for b in plan for z in (b, width[b])]), F.col("box"))
            here = df.where(F.col("box").isin(list(plan)))
            bin_ = F.floor((F.col("key") - lo_c) / w_c * bins).cast("int")
            hist = here.withColumn("bin", bin_).where(F.col("bin").between(0, bins - 1)).groupBy("box", "bin").agg(F.sum("w").alias("s")).collect()  # bins per box
            for b in plan:
                rows = sorted((r["bin"], r["s"]) for r in hist if r["box"] == b)
                if step == 0:
                    first, n = plan[b][1]
                    goal[b] = sum(s for _, s in rows) * (n // 2) / n
                at = 0
                for at, s in rows:  # noqa: B007
                    if under[b] + s > goal[b]:
                        break
                    under[b] += s
                else:
                    at += 1
                low[b] += at * width[b] / bins
                width[b] /= bins
        cut = F.element_at(F.create_map(*[F.lit(z) for b in plan for z in (b, low[b])]), F.col("box"))
        df = store(df.withColumn("box", F.when(F.col("box").isin(list(plan)), F.when(F.col("key") < cut, F.col("box") * 2 + 1).otherwise(F.col("box") * 2 + 2)).otherwise(F.col("box"))).drop("key"), "rcb")
        todo = {c: span for b, (_, (first, n)) in plan.items() for c, span in ((2 * b + 1, (first, n // 2)), (2 * b + 2, (first + n // 2, n - n // 2)))}
    label = F.element_at(F.create_map(*[F.lit(z) for b, k in final.items() for z in (b, k)]), F.col("box"))
    return df.select("v", label.cast("int").alias("k"))


#: Moves into one part are ranked in this many groups at most, so that no task holds all of them.
MOVE_GROUPS = 256


def refine(edges: DataFrame, part: DataFrame, weight: DataFrame, n_dom: int, eps: float = 0.03, rounds: int = 4) -> DataFrame:
    """Move boundary vertices to the part where most of their neighbours are, within the balance bound.

    Rounds alternate between moves to higher and to lower parts, so two neighbours never swap. Room in
    a part is given out by gain: moves are summed by (part, gain group) first, whole groups fit or not, and only the group
    in which the room ends is ranked vertex by vertex. In parts above the bound vertices may leave at a loss, the
    least loss first, until the bound is met. Edges may carry a column ``c`` with their number.
    """
    return _refine(_adjacency(edges, "refine-edges"), part, weight, n_dom, eps, rounds)


def _adjacency(edges: DataFrame, name: str) -> DataFrame:
    """Stored rows (i, j, c): both directions of every edge once with its number, the rows of a vertex in one place."""
    c = (F.col("c") if "c" in edges.columns else F.lit(1.0)).cast("double")
    ways = F.explode(F.array(F.struct(F.col("i"), F.col("j"), c.alias("c")), F.struct(F.col("j").alias("i"), F.col("i").alias("j"), c.alias("c"))))
    both = edges.where("i <> j").select(ways.alias("z")).select("z.*")
    return store(both.repartition("i").groupBy("i", "j").agg(F.sum("c").alias("c")), name)


def _spread(vertex: DataFrame, n: int) -> DataFrame:
    """A table of n vertices for a join with edges, which stay where they are unless it is too large."""
    return F.broadcast(vertex) if n <= SPREAD else vertex


def _refine(both: DataFrame, part: DataFrame, weight: DataFrame, n_dom: int, eps: float, rounds: int) -> DataFrame:
    total, n = weight.agg(F.sum("w"), F.count(F.lit(1))).first()
    cap = (1 + eps) * (total or 0.0) / n_dom
    part = store(part.select("v", F.col("k").cast("int").alias("k")), "refine-part")
    idle = 0
    for r in range(rounds):
        load = {x["k"]: x["load"] for x in part.join(weight, "v").groupBy("k").agg(F.sum("w").alias("load")).collect()}  # one row a part
        loads = part.sparkSession.createDataFrame([(k, float(load.get(k, 0.0))) for k in range(n_dom)], "k int, load double")
        near = both.join(_spread(part.select(F.col("v").alias("j"), F.col("k").alias("kj")), n), "j").groupBy(F.col("i").alias("v"), "kj").agg(F.sum("c").alias("c"))
        own = near.join(part, "v").join(F.broadcast(loads), "k")
        ahead = F.col("kj") > F.col("k") if r % 2 == 0 else F.col("kj") < F.col("k")
        best = own.groupBy("v", "k", "load").agg(F.max_by("kj", F.when(ahead, F.struct("c", "kj"))).alias("to"), F.max(F.when(ahead, F.col("c"))).alias("outside"), F.max(F.when(F.col("kj") == F.col("k"), F.col("c"))).alias("inside"))
        gain = best.where("outside is not null").withColumn("gain", F.col("outside") - F.coalesce("inside", F.lit(0.0))).join(weight, "v")
        over = F.greatest(F.col("load") - cap, F.lit(0.0))
        gain = store(gain.where((F.col("gain") > 0) | (over > 0)).withColumn("over", over), "refine-gain")
        steps = [x for x in gain.approxQuantile("gain", [i / MOVE_GROUPS for i in range(1, MOVE_GROUPS)], 0.002)] if not gain.isEmpty() else []
        bounds = sorted(set(steps))
        group = F.lit(0) if not bounds else F.expr(f"size(filter(array({','.join(map(repr, bounds))}), b -> b < gain))")
        # leaving a full part is limited by what it has too much, entering one by its room
        moved = gain.withColumn("g", group)
        moved = _fitting(moved.withColumn("room", F.when(F.col("gain") > 0, F.lit(float("inf"))).otherwise(F.col("over"))), "k", enter=False)
        moved = store(moved, "refine-leave")
        moved = moved.drop("room").join(F.broadcast(loads.select(F.col("k").alias("to"), (F.lit(cap) - F.col("load")).alias("room"))), "to")
        moved = store(_fitting(moved, "to", enter=True).select("v", "to"), "refine-moves")
        idle = idle + 1 if moved.isEmpty() else 0
        if idle == 2:
            break
        part = store(part.join(moved, "v", "left").select("v", F.coalesce("to", "k").cast("int").alias("k")), "refine-part")
    return part


def _fitting(moves: DataFrame, by: str, enter: bool) -> DataFrame:
    """Moves (v, gain, g, w, room) whose weights, best gains first, fit the room of their part ``by``.

    Leaving goes on until the room (the excess) is used up; entering stops before it is exceeded.
    """
    free = moves.where(F.col("room") == float("inf"))
    tight = moves.where(F.col("room") < float("inf"))
    sums = tight.groupBy(by, "g").agg(F.sum("w").alias("s"))
    before = F.coalesce(F.sum("s").over(Window.partitionBy(by).orderBy(F.desc("g")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    placed = tight.join(F.broadcast(sums.withColumn("before", before)), [by, "g"])
    whole = placed.where(F.col("before") + F.col("s") <= F.col("room"))
    edge = placed.where((F.col("before") + F.col("s") > F.col("room")) & (F.col("before") < F.col("room")))
    used = F.col("before") + F.sum("w").over(Window.partitionBy(by, "g").orderBy(F.desc("gain"), "v"))
    edge = edge.withColumn("used", used).where((F.col("used") <= F.col("room")) if enter else (F.col("used") - F.col("w") < F.col("room"))).drop("used")
    return free.unionByName(whole.unionByName(edge).drop("before", "s"))


def _grow(n: int, i: np.ndarray, j: np.ndarray, c: np.ndarray, w: np.ndarray, n_dom: int) -> np.ndarray:
    """Greedy growing on the coarsest graph: parts take the best-connected vertex until their share is full."""
    nbr: list[list[tuple[int, float]]] = [[] for _ in range(n)]
    for a, b, x in zip(i.tolist(), j.tolist(), c.tolist(), strict=True):
        nbr[a].append((b, x))
        nbr[b].append((a, x))
    k = np.full(n, -1)
    left = w.sum()
    met = np.zeros(n)  # edges to parts that are full: the next part begins at their border
    for p in range(n_dom):
        goal, have = left / (n_dom - p), 0.0
        pull = np.zeros(n)
        free = np.flatnonzero(k < 0)
        if p == n_dom - 1:
            k[free] = p
            break
        while len(free) and have < goal:
            score = pull[free]
            v = int(free[np.argmax(score)]) if score.max(initial=0) > 0 else int(free[np.lexsort(([len(nbr[f]) for f in free], -met[free]))[0]])
            if have and have + w[v] - goal > goal - have:
                break
            k[v] = p
            have += w[v]
            for b, x in nbr[v]:
                pull[b] += x
            free = free[free != v]
        met += pull
        left -= have
    return k


#: Vertices that share a heaviest neighbour are paired in groups of about this many.
SIBLINGS = 1_000


def _siblings(rest: DataFrame, limit: float) -> DataFrame:
    """Pairs (v, to) of rows (v, w, hub) with one hub, light ones first; a hub of very many is split by a hash."""
    size = rest.groupBy("hub").agg(F.ceil(F.count(F.lit(1)) / SIBLINGS).alias("n"))
    rest = rest.join(size, "hub").withColumn("salt", F.pmod(F.xxhash64("v"), "n"))
    at = F.row_number().over(Window.partitionBy("hub", "salt").orderBy("w", "v"))
    two = rest.withColumn("at", F.floor((at - 1) / 2)).groupBy("hub", "salt", "at").agg(F.max("v").alias("v"), F.min("v").alias("to"), F.sum("w").alias("w"))
    return two.where((F.col("v") > F.col("to")) & (F.col("w") <= limit)).select("v", "to")


def partition_multilevel(edges: DataFrame, weight: DataFrame, n_dom: int, eps: float = 0.03, seed: int = 1, coarse: int = COARSE) -> DataFrame:
    """Match heavy edges and contract until the graph is small, split it, and refine at every level on the way back.

    While the graph is much too large, vertices join the centre (one vertex in eight, by a hash) to which they have most edges for its
    weight, as far as the weight bound of its cluster allows. Nearer the end, or where few have a centre beside them, vertices are paired:
    a vertex proposes to the neighbour with most edges for its weight (ties by a hash of the pair), among those with
    which it stays under the weight bound; mutual proposals merge. Where they merge few, as around a hub, the rest
    merges in pairs that share their first choice, and then those without any choice in pairs of all. Rounds go on until the
    graph has at most ``coarse`` vertices, which the driver splits by growing parts; when a round merges
    nearly nothing the weight bound, which starts at what gives evenly sized vertices, is doubled. It ends at a part's
    weight, where any two of the lighter half of more than 2 n_dom vertices may merge. So the bound is always reached.

    The graph of a level is stored with the rows of a vertex in one place, so a round moves one row a vertex (and part).
    """
    spark = edges.sparkSession
    v = store(weight.select("v", "w"), "ml-v")
    e = _adjacency(edges, "ml-e")
    total, n = v.agg(F.sum("w"), F.count(F.lit(1))).first()
    few = max(coarse, 4 * n_dom)
    most = (total or 0.0) / n_dom
    limit = min(most, 3.0 * (total or 0.0) / few)
    levels, maps = [(e, v)], []
    while n > few:
        pairs, merged = None, 0
        if n > CENTRES * few:
            pairs = store(_clusters(e, v, n, limit, seed + len(maps)), "ml-pairs")
            merged = pairs.count()
        if 2 * merged < n:  # few have a centre beside them, or the end is near
            pairs, merged = _pairs(e, v, n, limit, seed)
        if 20 * merged < n and limit < most:
            limit = min(most, 2 * limit)
            if not merged:
                continue
        if not merged:
            break  # all vertices but a few weigh more than half a part: nothing is left to coarsen
        step = store(v.select("v").join(pairs, "v", "left").select("v", F.coalesce("to", "v").alias("to")), "ml-map")
        maps.append(step)
        v = store(v.join(step, "v").groupBy(F.col("to").alias("v")).agg(F.sum("w").alias("w")), "ml-v")
        mi, mj = step.select(F.col("v").alias("i"), F.col("to").alias("ti")), step.select(F.col("v").alias("j"), F.col("to").alias("tj"))
        moved = e.join(_spread(mi, n), "i").join(_spread(mj, n), "j").where("ti <> tj").select(F.col("ti").alias("i"), F.col("tj").alias("j"), "c")
        e = store(moved.repartition("i").groupBy("i", "j").agg(F.sum("c").alias("c")), "ml-e")
        n = v.count()
        levels.append((e, v))
    if n > few:
        raise ValueError(f"{n} vertices are left, each near the weight of a part: the weights allow no balanced partition")
    vs, es = v.orderBy("v").toPandas(), e.where("i < j").orderBy("i", "j").toPandas()
    ids = vs["v"].to_numpy()
    i, j, w = np.searchsorted(ids, es["i"]), np.searchsorted(ids, es["j"]), vs["w"].to_numpy(float)
    k = _improve(_grow(len(ids), i, j, es["c"].to_numpy(float), w, n_dom), i, j, es["c"].to_numpy(float), w, n_dom, eps)
    part = spark.createDataFrame(list(zip(ids.tolist(), k.tolist(), strict=True)), "v long, k int")
    for step, (e, v) in zip(reversed(maps), reversed(levels[:-1]), strict=True):
        part = store(step.join(part.select(F.col("v").alias("to"), "k"), "to").select("v", "k"), "ml-part")
        if v is not levels[0][1]:
            part = _refine(e, part, v, n_dom, eps, rounds=2)
    return _refine(levels[0][0], part, levels[0][1], n_dom, eps, rounds=8)


def _choices(e: DataFrame, n: int, wi: DataFrame, wj: DataFrame, limit: float, seed: int) -> DataFrame:
    """Rows (i, j): of the vertices wj beside a vertex of wi that fit its weight, the one with most edges for its weight.

    The best ratio comes first, by itself, so that only rows that reach it are compared by their hash.
    """
    fit = e.join(_spread(wi, n), "i").join(_spread(wj, n), "j").where(F.col("wi") + F.col("wj") <= limit)
    rated = fit.select("i", "j", (F.col("c") / F.greatest(F.col("wj"), F.lit(1e-300))).alias("r"))
    top = store(rated.groupBy("i").agg(F.max("r").alias("top")), "ml-top")
    tie = F.xxhash64(F.least("i", "j"), F.greatest("i", "j"), F.lit(seed))
    return rated.join(_spread(top, n), "i").where("r = top").groupBy("i").agg(F.max_by("j", tie).alias("j"))


def _clusters(e: DataFrame, v: DataFrame, n: int, limit: float, seed: int) -> DataFrame:
    """Pairs (v, to) of vertices and the centres that they join; those of one centre stay under the weight bound together."""
    centre = F.pmod(F.xxhash64("v", F.lit(seed)), F.lit(CENTRES)) == 0
    wi = v.where(~centre).select(F.col("v").alias("i"), F.col("w").alias("wi"))
    wj = v.where(centre).select(F.col("v").alias("j"), F.col("w").alias("wj"))
    want = store(_choices(e, n, wi, wj, limit, seed).join(wi, "i").join(wj, "j"), "ml-want")
    # the room of a centre that very many choose is dealt out in shares
    size = want.groupBy("j").agg(F.ceil(F.count(F.lit(1)) / SIBLINGS).alias("n"))
    dealt = want.join(size, "j").withColumn("salt", F.pmod(F.xxhash64("i"), "n"))
    used = F.sum("wi").over(Window.partitionBy("j", "salt").orderBy("wi", "i"))
    return dealt.withColumn("used", used).where(F.col("used") <= (F.lit(limit) - F.col("wj")) / F.col("n")).select(F.col("i").alias("v"), F.col("j").alias("to"))


def _pairs(e: DataFrame, v: DataFrame, n: int, limit: float, seed: int) -> tuple[DataFrame, int]:
    """Pairs (v, to) of vertices that merge, and their number."""
    wi, wj = v.select(F.col("v").alias("i"), F.col("w").alias("wi")), v.select(F.col("v").alias("j"), F.col("w").alias("wj"))
    want = store(_choices(e, n, wi, wj, limit, seed), "ml-want")
    pairs = want.alias("a").join(want.alias("b"), (F.col("a.i") == F.col("b.j")) & (F.col("a.j") == F.col("b.i"))).where("a.i < a.j").select(F.col("a.j").alias("v"), F.col("a.i").alias("to"))
    pairs = store(pairs, "ml-pairs")
    merged = pairs.count()
    for lone in (False, True):  # pairs with one first choice, then those with none
        if 4 * merged >= n:
            break
        met = pairs.select(F.explode(F.array("v", "to")).alias("v"))
        rest = v.join(met, "v", "left_anti").join(want.select(F.col("i").alias("v"), F.col("j").alias("hub")), "v", "left")
        rest = rest.where(F.col("hub").isNull()).withColumn("hub", F.lit(-1).cast("long")) if lone else rest.where(F.col("hub").isNotNull())
        more = store(_siblings(store(rest, "ml-rest"), limit), "ml-more")
        merged += more.count()
        pairs = store(pairs.unionByName(more), "ml-pairs")
    return pairs, merged


def _improve(k: np.ndarray, i: np.ndarray, j: np.ndarray, c: np.ndarray, w: np.ndarray, n_dom: int, eps: float, rounds: int = 20) -> np.ndarray:
    """Single moves on the coarsest graph, best gain first, under the balance bound; parts above it are emptied to it."""
    k = k.copy()
    cap = (1 + eps) * w.sum() / n_dom
    tie = np.zeros((len(w), n_dom))
    np.add.at(tie, (i, k[j]), c)
    np.add.at(tie, (j, k[i]), c)
    near: list[list[tuple[int, float]]] = [[] for _ in w]
    for a, b, x in zip(i.tolist(), j.tolist(), c.tolist(), strict=True):
        near[a].append((b, x))
        near[b].append((a, x))
    load = np.bincount(k, weights=w, minlength=n_dom)
    for _ in range(rounds):
        moves = 0
        gain = tie.max(1) - tie[np.arange(len(w)), k]
        for a in np.lexsort((np.arange(len(w)), -gain)):
            mine = k[a]
            room = load + w[a] <= cap
            room[mine] = False
            if not room.any():
                continue
            to = int(np.argmax(np.where(room, tie[a], -np.inf)))
            better = tie[a, to] - tie[a, mine]
            if better > 0 or load[mine] > cap:
                k[a] = to
                load[mine] -= w[a]
                load[to] += w[a]
                for b, x in near[a]:
                    tie[b, mine] -= x
                    tie[b, to] += x
                moves += 1
        if not moves:
            break
    return k


# ---- measures ------------------------------------------------------------------------------


def cut_sizes(edges: DataFrame, parts: dict[str, DataFrame]) -> DataFrame:
    """One row: edges in all, and by name those that each of several partitions of the same vertices cuts; one pass over the edges."""
    both = None
    for name, p in parts.items():
        p = p.select("v", F.col("k").alias(name))
        both = p if both is None else both.join(p, "v")
    both = store(both, "cut-parts")
    at = lambda end: _spread(both.select(F.col("v").alias(end), F.struct(*parts).alias(f"k{end}")), n)
    n = both.count()
    got = edges.where("i <> j").select("i", "j").join(at("i"), "i").join(at("j"), "j")
    return got.agg(F.count(F.lit(1)).alias("n_edges"), *[F.count_if(F.col(f"ki.{p}") != F.col(f"kj.{p}")).alias(p) for p in parts])


def cut_size(edges: DataFrame, part: DataFrame) -> DataFrame:
    """One row: edges in all, and those whose ends lie in different parts."""
    e = edges.where("i <> j").select("i", "j")
    got = e.join(part.select(F.col("v").alias("i"), F.col("k").alias("ki")), "i").join(part.select(F.col("v").alias("j"), F.col("k").alias("kj")), "j")
    return got.agg(F.count(F.lit(1)).alias("n_edges"), F.count_if(F.col("ki") != F.col("kj")).alias("cut"))


def balance(weight: DataFrame, part: DataFrame, n_dom: int, eps: float = 0.03) -> DataFrame:
    """Rows (k, n, w, share, within): weights of parts against the relaxed bounds; violations are reported, not raised."""
    per = weight.join(part, "v").groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("w"))
    total = weight.agg(F.sum("w").alias("total"))
    mean = F.col("total") / n_dom
    return per.crossJoin(F.broadcast(total)).select("k", "n", "w", (F.col("w") / mean).alias("share"), ((F.col("w") <= (1 + eps) * mean) & (F.col("w") >= mean / (1 + eps))).alias("within"))
