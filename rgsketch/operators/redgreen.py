"""The red-green sampler: the hash of a vector is the index (from 1) of the first shared draw on its green area."""

from __future__ import annotations

import bisect
import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rgsketch.plans import darts as D
from rgsketch.plans.layout import Layout, horizon, unit_layout
from rgsketch.sources.tables import materialize

HASHES = "vec_id long, hash_id int, h int"
#: Draws that a first horizon has at most, over all hashes; what it leaves open is drawn on.
MAX_DRAWS = 4_000_000


def is_green_scan(r: Column, starts: Column, weights: Column) -> Column:
    """Membership by a scan of the vector's green stretches."""
    return F.exists(F.arrays_zip(starts.alias("s"), weights.alias("w")), lambda e: (e["s"] <= r) & (r < e["s"] + e["w"]))


def is_green_search(r: Column, starts: Column, weights: Column) -> Column:
    """Membership by the last ascending start that isn't above r (halving the range for each of its log2 steps)."""
    n = F.size(starts)

    def halve(acc, _):
        mid = F.floor((acc["lo"] + acc["hi"] + 1) / 2).cast("int")
        up = F.element_at(starts, F.greatest(mid, F.lit(1))) <= r
        return F.when(acc["lo"] < acc["hi"], F.struct(F.when(up, mid).otherwise(acc["lo"]).alias("lo"), F.when(up, acc["hi"]).otherwise(mid - 1).alias("hi"))).otherwise(acc)

    at = F.aggregate(F.sequence(F.lit(0), F.lit(31)), F.struct(F.lit(0).alias("lo"), n.alias("hi")), halve)["lo"]
    return F.when(at >= 1, r < F.element_at(starts, F.greatest(at, F.lit(1))) + F.element_at(weights, F.greatest(at, F.lit(1)))).otherwise(F.lit(False))


def is_green_table(r: Column, cells: Column, starts: Column, weight_of: Column) -> Column:
    """Membership in constant time: cell of r to component, component to start; weight_of is a map of the vector."""
    comp = F.element_at(cells, F.floor(r).cast("int") + 1)
    return r - F.element_at(starts, comp + 1) < F.coalesce(F.try_element_at(weight_of, comp), F.lit(0.0))


def sketch_relational(v: DataFrame, darts: DataFrame, alpha: float = 1.0, small: bool = True) -> DataFrame:
    """vec_id, hash_id, h of the resolved pairs: a join with the darts and a minimum, partial before the one exchange.

    ``small`` sends the darts (k * steps rows, pruned) to all executors; without it the join shuffles on the component.
    """
    side = F.broadcast(darts) if small else darts
    hit = v.join(side, "comp").where(F.col("offset") < F.col("weight") * F.lit(float(alpha)))
    return hit.groupBy("vec_id", "hash_id").agg(F.min("step").alias("h"))


def full_horizon(v: DataFrame, layout: Layout, k: int, delta: float = 1e-9) -> int:
    """Draws after which a hash of the least filled vector is open with probability ``delta``, MAX_DRAWS over all k at most."""
    low = v.groupBy("vec_id").agg(F.sum("weight").alias("l")).agg(F.min("l").alias("l")).first()["l"]
    return max(1, min(horizon(min(1.0, (low or 1.0) * layout.alpha / max(layout.total, 1e-300)), delta), MAX_DRAWS // k))


def sketch(v: DataFrame, layout: Layout, k: int, seed: int, delta: float = 1e-6, steps: int | None = None, unresolved: str = "extend", empty: str = "null", broadcast_rows: int = 2_000_000) -> DataFrame:
    """All hashes of all vectors. Pairs without a green draw within the horizon are drawn on (``extend``, exact) or get
    h = 0, equal to nothing (``cap``). Without ``steps`` the horizon follows the least fill, so that a pair of it is open
    with probability ``delta``. Vectors without weight aren't in long form; see ``with_empty``."""
    steps = full_horizon(v, layout, k, delta) if steps is None else steps
    pruned = D.drop_dead(D.prune(D.build(layout, k, steps, seed)), layout)
    pruned = materialize(pruned)
    found = sketch_relational(v, pruned, layout.alpha, pruned.count() <= broadcast_rows)
    if unresolved == "extend":
        return extend(v, found, layout, k, seed, steps)
    grid = v.select("vec_id").distinct().crossJoin(F.broadcast(v.sparkSession.range(k).select(F.col("id").cast("int").alias("hash_id"))))
    return grid.join(found, ["vec_id", "hash_id"], "left").select("vec_id", "hash_id", F.coalesce("h", F.lit(0)).alias("h"))


def extend(v: DataFrame, found: DataFrame, layout: Layout, k: int, seed: int, steps: int, rounds: int = 24) -> DataFrame:
    """Draw on for the (vector, hash) pairs without a hash, doubling the horizon each round until none is left."""
    found = materialize(found)
    hashes = F.broadcast(v.sparkSession.range(k).select(F.col("id").cast("int").alias("hash_id")))
    short = found.groupBy("vec_id").count().where(F.col("count") < k).select("vec_id").unionByName(v.select("vec_id").join(found, "vec_id", "left_anti").distinct())
    open_ = materialize(short.crossJoin(hashes).join(found, ["vec_id", "hash_id"], "left_anti"))
    for _ in range(rounds):
        if open_.isEmpty():
            return found
        more = D.drop_dead(D.prune(D.build(layout, k, steps, seed, steps + 1)), layout)
        rest = v.join(open_, "vec_id").join(more, ["hash_id", "comp"]).where(F.col("offset") < F.col("weight") * F.lit(float(layout.alpha)))
        got = materialize(rest.groupBy("vec_id", "hash_id").agg(F.min("step").alias("h")))
        found = found.unionByName(got)
        open_ = materialize(open_.join(got, ["vec_id", "hash_id"], "left_anti"))
        steps *= 2
    raise RuntimeError("pairs are left without a green draw; is a vector outside its layout?")


def with_empty(sketches: DataFrame, ids: DataFrame, empty: str = "null") -> DataFrame:
    """Add the ids that have no hash: as one row with nulls, or as an error."""
    gone = ids.select("vec_id").distinct().join(sketches.select("vec_id"), "vec_id", "left_anti")
    h = F.lit(None).cast("int")
    if empty == "error":
        h = F.raise_error(F.lit("a vector without weight has no hash")).cast("int")
    return sketches.unionByName(gone.select("vec_id", F.lit(None).cast("int").alias("hash_id"), h.alias("h")))


def dart_arrays(darts: DataFrame, k: int, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """k x steps components and offsets; at most k * steps numbers come to the driver, a size the caller chooses."""
    if k * steps > 20_000_000:
        raise ValueError("k * steps is too large to send; use the relational plan")
    got = darts.toArrow()
    comp, off = np.zeros((k, steps), np.int64), np.full((k, steps), np.inf)
    h, t = got.column("hash_id").to_numpy(), got.column("step").to_numpy() - 1
    comp[h, t], off[h, t] = got.column("comp").to_numpy(), got.column("offset").to_numpy()
    return comp, off


def first_green(w: np.ndarray, comp: np.ndarray, off: np.ndarray, block: int = 8) -> np.ndarray:
    """Rows of weights (by component) to rows of hashes; 0 where no draw is green. Resolved pairs leave the work."""
    n, (k, steps) = len(w), comp.shape
    out = np.zeros((n, k), np.int32)
    row, hash_ = (x.ravel() for x in np.indices((n, k)))
    for t in range(0, steps, block):
        if not len(row):
            break
        c, o = comp[:, t : t + block], off[:, t : t + block]
        green = w[row[:, None], c[hash_]] > o[hash_]
        any_ = green.any(1)
        out[row[any_], hash_[any_]] = t + 1 + green[any_].argmax(1)
        row, hash_ = row[~any_], hash_[~any_]
        block = min(block * 2, 64)
    return out


def sketcher(layout: Layout, k: int, steps: int, seed: int, rows: int = 256):
    """The function over Arrow batches (vec_id, comps, weights) that ``sketch_batches`` runs in the workers."""
    comp, off = dart_arrays(D.build(layout, k, steps, seed), k, steps)
    named = np.unique(comp)
    comp = np.searchsorted(named, comp).astype(np.int32)
    alpha = layout.alpha

    def run(batches):
        for batch in batches:
            ids, comps, weights = batch.columns
            sizes = np.asarray(comps.value_lengths().fill_null(0)).astype(np.int64)
            c, x = np.asarray(comps.flatten()).astype(np.int64), np.asarray(weights.flatten()) * alpha
            at, edge = np.searchsorted(named, c), np.concatenate(([0], np.cumsum(sizes)))
            ok = (at < len(named)) & (named[np.minimum(at, len(named) - 1)] == c) if len(named) else np.zeros(len(c), bool)
            out = []
            for lo in range(0, batch.num_rows, rows):
                hi = min(lo + rows, batch.num_rows)
                w = np.zeros((hi - lo, len(named)))
                s = slice(edge[lo], edge[hi])
                r = np.repeat(np.arange(hi - lo), sizes[lo:hi])
                w[r[ok[s]], at[s][ok[s]]] = x[s][ok[s]]
                out.append(first_green(w, comp, off))
            h = np.concatenate(out) if out else np.zeros((0, k), np.int32)
            offsets = pa.array(np.arange(0, h.size + 1, k, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(offsets, pa.array(h.ravel()))], ["vec_id", "sketch"])

    return run


def sketch_batches(packed: DataFrame, layout: Layout, k: int, steps: int, seed: int, rows: int = 256) -> DataFrame:
    """vec_id, sketch ARRAY<INT> from packed vectors: Arrow batches, every pair stops at its first green draw; 0 if none.

    A batch's weights are spread over the components that the darts name, ``rows`` vectors at a time, so that a worker's
    memory is rows * (named components).
    """
    return packed.select("vec_id", "comps", "weights").mapInArrow(sketcher(layout, k, steps, seed, rows), "vec_id long, sketch array<int>")


def sketch_one(comps: list[int], weights: list[float], layout: list[tuple[int, float, float]], k: int, seed: int, test: str = "search", stream: str = "counter", limit: int = 1_000_000) -> list[int]:
    """One vector in plain Python, for teaching and tests. layout has (comp, cap, lo) by lo; test is scan, search or table;
    stream is counter (draws keyed by seed, hash and step) or chained (each draw seeds the next)."""
    total = layout[-1][1] + layout[-1][2]
    weight = dict(zip(comps, weights, strict=True))
    starts = [lo for _, _, lo in layout]
    cells = [c for c, (_, cap, _) in enumerate(layout) for _ in range(int(cap))] if test == "table" else None

    def green(r: float) -> bool:
        if test == "scan":
            return any(lo <= r < lo + weight.get(c, 0.0) for c, _, lo in layout)
        i = cells[math.floor(r)] if test == "table" else bisect.bisect_right(starts, r) - 1
        return r - starts[i] < weight.get(layout[i][0], 0.0)

    def u(*key) -> float:
        return int(hashlib.md5(":".join(map(str, key)).encode()).hexdigest()[:13], 16) / 2**52

    out = []
    for h in range(k):
        step, r = 1, (u(seed, h, 1) if stream == "counter" else u(seed, "chain", h)) * total
        while not green(r):
            if step >= limit:
                raise RuntimeError("no green draw")
            step += 1
            r = (u(seed, h, step) if stream == "counter" else u("next", math.ceil(r * D.MULTIPLIER))) * total
        out.append(step)
    return out


def sketch_sets(sets: DataFrame, k: int, steps: int, seed: int, id_col: str = "vec_id", array_col: str = "items", unresolved: str = "cap") -> tuple[DataFrame, Layout]:
    """Sets of whole numbers as vectors of ones: their sketches, and the layout that they compare under."""
    v = sets.select(F.col(id_col).alias("vec_id"), F.explode(F.array_distinct(F.col(array_col).cast("array<int>"))).alias("comp"), F.lit(1.0).alias("weight"))
    layout = unit_layout(v)
    return sketch(v, layout, k, seed, steps=steps, unresolved=unresolved), layout


def to_packed(hashes: DataFrame) -> DataFrame:
    """vec_id, sketch ARRAY<INT> in order of hash_id."""
    got = hashes.groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("hash_id", "h"))).alias("e"))
    return got.select("vec_id", F.col("e.h").alias("sketch"))


def to_long(packed: DataFrame) -> DataFrame:
    return packed.select("vec_id", F.posexplode("sketch").alias("hash_id", "h"))


def merge_max(hashes: DataFrame, group: DataFrame) -> DataFrame:
    """The sketch of each group's element-wise maximum, from its members' hashes: group has vec_id and group_id."""
    return hashes.join(group, "vec_id").groupBy(F.col("group_id").alias("vec_id"), "hash_id").agg(F.min("h").alias("h"))


def update(hashes: DataFrame, grown: DataFrame, darts: DataFrame, alpha: float = 1.0) -> DataFrame:
    """Hashes after some weights grew within their widths: only darts between the old and the new weight can lower one.
    grown has vec_id, comp, old_weight, new_weight."""
    w = F.lit(float(alpha))
    new = grown.join(darts, "comp").where((F.col("offset") >= F.col("old_weight") * w) & (F.col("offset") < F.col("new_weight") * w))
    low = new.groupBy("vec_id", "hash_id").agg(F.min("step").alias("h"))
    return hashes.unionByName(low).groupBy("vec_id", "hash_id").agg(F.min("h").alias("h"))


def sql(v: str = "v", darts: str = "darts", name: str = "rg", alpha: float = 1.0) -> str:
    return f"{name} AS (SELECT vec_id, hash_id, min(step)::INT AS h FROM {v} JOIN {darts} USING (comp) WHERE off < weight * {float(alpha)}::DOUBLE GROUP BY vec_id, hash_id)"
