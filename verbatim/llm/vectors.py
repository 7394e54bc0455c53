"""Embedding near-duplicates by PCA-ordered tiled comparison.

Vectors of one label are sorted by their first principal component and cut into slabs, and each
slab by the second into tiles, as many to a slab as there are slabs. A tile's ranges on the
leading axes are its box; tiles whose boxes lie farther apart than the distance that the
threshold allows are never paired. Within a pair of tiles, dot products are summed over leading principal
dimensions first; what the other dimensions can add is bounded by the product of their norms
(Cauchy-Schwarz), and a pair is given up once the bound falls below the threshold. Survivors
are decided by the cosine of the original components in double precision.

Equal vectors of a label are compared once and counted; a pair of tiles returns counts and
the links that span its parts, not its pairs.

Defined results: vectors that are null, empty, zero, or hold null or non-finite components,
and those without a label, link with nothing; vectors of other lengths are not compared;
an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

#: Rows of a tile; leading axes of its box.
COSINE, TILE, AXES = 0.93, 1024, 8


def _unit(e) -> np.ndarray:
    x = np.array(list(e), dtype=np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def principal_axes(reps: DataFrame) -> dict[int, np.ndarray]:
    """For each vector length, axes by falling variance, from all vectors; d * d sums reach the driver."""

    def partial(batches):
        for b in batches:
            for d, g in b.groupby("_d"):
                u = _unit(g["_e"])
                yield pd.DataFrame({"_d": [d], "_s": [(u.T @ u).ravel()]})

    sums = reps.select("_d", "_e").mapInPandas(partial, "_d int, _s array<double>").select("_d", F.posexplode("_s").alias("_i", "_x")).groupBy("_d", "_i").agg(F.sum("_x").alias("_x")).toPandas()
    axes = {}
    for d, g in sums.groupby("_d"):
        m = np.zeros(d * d)
        m[g["_i"]] = g["_x"]
        axes[int(d)] = np.linalg.eigh(m.reshape(d, d))[1][:, ::-1]
    return axes


def near(a: np.ndarray, b: np.ndarray, least: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """Candidate pairs of two tiles of rotated unit vectors: all with cosine >= least, few others."""
    d = a.shape[1]
    slack = least - 1e-7
    tails = lambda m: np.sqrt(np.maximum(np.cumsum((m * m)[:, ::-1], axis=1)[:, ::-1], 0))
    ta, tb = tails(a), tails(b)
    stops = sorted({min(d, s) for s in (8, 16, 32)} | {d})
    dots, at, i = np.zeros((len(a), len(b))), 0, None
    for stop in stops:
        rest = (ta[:, stop], tb[:, stop]) if stop < d else (np.zeros(len(a)), np.zeros(len(b)))
        if i is None:
            dots += a[:, at:stop] @ b[:, at:stop].T
            alive = dots + rest[0][:, None] * rest[1][None, :] >= slack
            if same:
                alive = np.triu(alive, 1)
            if alive.sum() < 0.02 * alive.size or stop == d:
                i, j = np.nonzero(alive)
                dots = dots[i, j]
        else:
            dots = dots + np.einsum("ij,ij->i", a[i, at:stop], b[j, at:stop])
            alive = dots + rest[0][i] * rest[1][j] >= slack
            i, j, dots = i[alive], j[alive], dots[alive]
        at = stop
    return i, j


def compare(tile: pd.DataFrame, axes: np.ndarray, least: float) -> pd.DataFrame:
    """Link counts and spanning links of one pair of tiles, the rows of both with side 0 and 1 (or one tile, all 0)."""
    tile = tile.sort_values(["_side", "_v"])
    ids, count, e = tile["_v"].to_numpy(), tile["_n"].to_numpy(), np.array(list(tile["_e"]), dtype=np.float64)
    u = _unit(e) @ axes
    cut = int((tile["_side"] == 0).sum())
    same = cut == len(tile)
    i, j = near(u[:cut], u if same else u[cut:], least, same)
    j = j if same else j + cut
    keep = np.zeros(len(i), dtype=bool)
    for at in range(0, len(i), 1 << 16):
        x, y = e[i[at : at + (1 << 16)]], e[j[at : at + (1 << 16)]]
        keep[at : at + (1 << 16)] = (x * y).sum(axis=1) / (np.sqrt((x * x).sum(axis=1)) * np.sqrt((y * y).sum(axis=1))) >= least
    i, j = i[keep], j[keep]
    n = np.bincount(i, count[j], len(ids)) + np.bincount(j, count[i], len(ids))
    root = np.arange(len(ids))
    while True:
        new = root.copy()
        np.minimum.at(new, i, root[j])
        np.minimum.at(new, j, root[i])
        new = np.minimum(new, new[new])
        if (new == root).all():
            break
        root = new
    some = n > 0
    return pd.DataFrame({"_v": ids[some], "_links": n[some].astype(np.int64), "_to": ids[root][some]})


def components(emb: DataFrame, least: float = COSINE, tile: int = TILE) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of emb(vec_id, embedding, label)."""
    e = F.col("embedding")
    sound = F.col("label").isNotNull() & e.isNotNull() & (F.size(e) > 0) & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(e, lambda x: x != 0)
    rows = emb.select("vec_id", "label", F.coalesce(sound, F.lit(False)).alias("_ok"), F.xxhash64("embedding").alias("_h1"), F.xxhash64(F.lit(7), F.col("embedding")).alias("_h2"), "embedding")
    key = ["label", "_h1", "_h2"]
    reps = rows.where("_ok").groupBy(*key).agg(F.min("vec_id").alias("_rep"), F.count(F.lit(1)).alias("_n"), F.first("embedding").alias("_e")).withColumn("_d", F.size("_e"))
    reps = C.cut(reps)
    axes = principal_axes(reps)

    @F.pandas_udf("array<double>")
    def lead(col: pd.Series) -> pd.Series:
        out = np.zeros((len(col), AXES))
        length = col.map(len)
        for d in set(length):
            at = (length == d).to_numpy()
            out[at, : min(d, AXES)] = _unit(col[at]) @ axes[d][:, :AXES]
        return pd.Series(list(out))

    # places are found for keys and leading components alone; vectors move once, to their pairs of tiles
    group = ["label", "_d"]
    slim = C.cut(reps.select(*group, "_h1", "_h2", "_rep", "_n", lead("_e").alias("_p")))
    by = lambda *within: [*map(F.col, group), *within, F.col("_h1"), F.col("_h2")]
    slim = C.cut(C.global_index(slim, by(F.get("_p", F.lit(0))), "_i"))
    starts = C.cut(slim.groupBy(*group).agg(F.min("_i").alias("_i0"), F.count(F.lit(1)).alias("_m")))
    thick = F.ceil(F.sqrt(F.ceil(F.col("_m") / tile))) * tile  # rows of a slab: as many tiles as there are slabs
    slim = slim.join(C.maybe_broadcast(starts), group).withColumn("_s", F.floor((F.col("_i") - F.col("_i0")) / thick)).drop("_i", "_m")
    # both orders begin with the group, so its first place is the same, and slabs are whole numbers of tiles
    slim = C.global_index(slim, by(F.col("_s"), F.get("_p", F.lit(1))), "_v")
    placed = C.cut(slim.withColumn("_t", F.floor((F.col("_v") - F.col("_i0")) / tile)).drop("_i0"))
    box = lambda f, name: F.array(*[f(F.get("_p", F.lit(k))) for k in range(AXES)]).alias(name)
    tiles = C.cut(placed.groupBy(*group, "_s", "_t").agg(box(F.min, "_lo"), box(F.max, "_hi")))
    reach = float(np.sqrt(2 - 2 * least)) + 1e-6
    slabs = C.cut(tiles.groupBy(*group, "_s").agg(F.min(F.get("_lo", F.lit(0))).alias("_a"), F.max(F.get("_hi", F.lit(0))).alias("_b")))
    near_slabs = slabs.join(slabs.select(*group, F.col("_s").alias("_s2"), F.col("_a").alias("_a2")), group).where((F.col("_s2") >= F.col("_s")) & (F.col("_a2") - F.col("_b") <= reach)).select(*group, "_s", "_s2")
    other = tiles.select(*group, F.col("_s").alias("_s2"), F.col("_t").alias("_t2"), F.col("_lo").alias("_lo2"), F.col("_hi").alias("_hi2"))
    gap = lambda k: F.greatest(F.lit(0.0), F.get("_lo2", F.lit(k)) - F.get("_hi", F.lit(k)), F.get("_lo", F.lit(k)) - F.get("_hi2", F.lit(k)))
    apart = sum((gap(k) * gap(k) for k in range(1, AXES)), gap(0) * gap(0))
    pairs = tiles.join(near_slabs, [*group, "_s"]).join(other, [*group, "_s2"]).where((F.col("_t2") >= F.col("_t")) & (apart <= reach * reach))
    sides = F.when(F.col("_t") == F.col("_t2"), F.array(F.struct(F.lit(0).alias("s"), F.col("_t").alias("t")))).otherwise(F.array(F.struct(F.lit(0).alias("s"), F.col("_t").alias("t")), F.struct(F.lit(1).alias("s"), F.col("_t2").alias("t"))))
    sides = pairs.select("label", "_d", F.concat_ws("/", "label", "_d", "_t", "_t2").alias("_pair"), F.explode(sides).alias("_x")).select("label", "_d", "_pair", F.col("_x.s").alias("_side"), F.col("_x.t").alias("_t"))
    vectors = reps.select("label", "_d", "_h1", "_h2", "_e").join(placed.select("label", "_d", "_h1", "_h2", "_t", "_v", "_n"), ["label", "_d", "_h1", "_h2"])
    dealt = vectors.join(C.maybe_broadcast(C.cut(sides)), ["label", "_d", "_t"])
    told = dealt.select("_pair", "_side", "_v", "_n", "_e", "_d").groupBy("_pair").applyInPandas(lambda g: compare(g, axes[int(g["_d"].iloc[0])], least), "_v long, _links long, _to long")
    told = C.cut(told)
    label = C.connected(told.select(F.col("_v").alias("a"), F.col("_to").alias("b")))
    counts = told.groupBy(F.col("_v").alias("_w")).agg(F.sum("_links").alias("_links"))
    known = placed.select(*[F.col(c).alias(f"_{c}") for c in key], "_v", "_n", "_rep")
    known = known.join(counts, F.col("_v") == F.col("_w"), "left").join(label, F.col("_v") == F.col("node"), "left")
    known = C.cut(known.select("__h1", "__h2", "_label", "_n", "_rep", "_links", "component"))
    least_id = known.where("component is not null").groupBy(F.col("component").alias("_cc")).agg(F.min("_rep").alias("_least"))
    known = known.join(least_id, F.col("component") == F.col("_cc"), "left")
    out = rows.drop("embedding").join(known, F.col("_ok") & (F.col("label") == F.col("_label")) & (F.col("_h1") == F.col("__h1")) & (F.col("_h2") == F.col("__h2")), "left")
    out = out.select("vec_id", (F.coalesce("_links", F.lit(0)) + F.coalesce(F.col("_n") - 1, F.lit(0))).cast("long").alias("n_links"), F.coalesce("_least", "_rep", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))


def op6_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(C.table(spark, sf_dir, "embeddings"))


def oracle() -> str:
    return f"""
WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= {COSINE}),
r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
c AS (SELECT a, min(b) AS m FROM r GROUP BY a),
n AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, least(vec_id, coalesce(m, vec_id))::BIGINT AS component_id, vec_id = least(vec_id, coalesce(m, vec_id)) AS kept
FROM embeddings LEFT JOIN c ON c.a = vec_id LEFT JOIN n ON n.a = vec_id
"""
