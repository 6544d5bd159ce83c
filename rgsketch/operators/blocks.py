"""All pairs of a set of vectors or sketches, block by block.

A join on components makes a row for every component that a pair shares, and exchanges them all. Here vectors are dealt to
blocks, and one task computes all pairs of two blocks in memory, so nothing but the blocks themselves is exchanged or
written, whatever the number of pairs. Weights must be above 0.
"""

from __future__ import annotations

import io
from collections.abc import Callable
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.sources.tables import materialize

#: Vectors and bytes of a block, about; bytes of a partition of blocks, and how many of these there are at least.
ROWS, BYTES, PART_BYTES, PARTS = 512, 4 << 20, 16 << 20, 12
#: Vectors that meet the other block at once, so that their table stays in a core's cache.
STRIP = 64
#: Shared components that are expanded at once.
EXPAND = 1 << 21
PAIR = "id_a long, id_b long, j double, l1_a double, l1_b double"


class Block:
    """Vectors by ascending component: ``row`` and ``weight`` from at[i] to at[i + 1] are those of comps[i]."""

    def __init__(self, data: bytes):
        t = np.load(io.BytesIO(data))
        self.ids, self.l1, self.row, self.weight = t["ids"], t["l1"], t["row"], t["weight"]
        self.sketch = t["sketch"].T.copy()  # hash by hash
        first = np.flatnonzero(np.diff(t["comp"], prepend=t["comp"][:1] - 1))
        self.comps, self.at = t["comp"][first], np.append(first, len(t["comp"]))

    def column(self, i: int) -> np.ndarray:
        out = np.zeros(len(self.ids))
        out[self.row[self.at[i] : self.at[i + 1]]] = self.weight[self.at[i] : self.at[i + 1]]
        return out


def _pack_block(key, t):
    """The Arrow table of a block's packed vectors as one row of bytes."""
    n = t.num_rows
    flat = lambda name, kind: np.concatenate([np.zeros(0, kind), *(c.flatten().to_numpy(zero_copy_only=False) for c in t.column(name).chunks)])
    comp, weight = flat("comps", np.int64), flat("weights", np.float64)
    row = np.repeat(np.arange(n, dtype=np.int32), t.column("d").to_numpy())
    order = np.argsort(comp, kind="stable")
    out = io.BytesIO()
    sketch = flat("sketch", t.schema.field("sketch").type.value_type.to_pandas_dtype()).reshape(n, -1)
    np.savez(out, ids=t.column("vec_id").to_numpy(), l1=np.bincount(row, weight, minlength=n).astype(np.float64), comp=comp[order], row=row[order], weight=weight[order], sketch=sketch)
    return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "data": pa.array([out.getvalue()], pa.binary())})


def _sparse(a: Block, b: Block, ia: np.ndarray, ib: np.ndarray, lo: np.ndarray) -> None:
    """Add the minima at the given common components, whose holders are few."""
    ca, cb = a.at[ia + 1] - a.at[ia], b.at[ib + 1] - b.at[ib]
    end = np.cumsum(ca * cb)
    at = 0
    while at < len(ia):
        to = max(at + 1, int(np.searchsorted(end, (end[at - 1] if at else 0) + EXPAND, side="right")))
        s = slice(at, to)
        size = ca[s] * cb[s]
        k = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        width = np.repeat(cb[s], size)
        x, y = np.repeat(a.at[ia[s]], size) + k // width, np.repeat(b.at[ib[s]], size) + k % width
        np.add.at(lo.reshape(-1), a.row[x].astype(np.int64) * lo.shape[1] + b.row[y], np.minimum(a.weight[x], b.weight[y]))
        at = to


def _minima(a: Block, b: Block):
    """Sums of minima of all pairs, strip by strip: (first row of a, rows x all of b)."""
    lo = np.zeros((len(a.ids), len(b.ids)))
    at = np.searchsorted(b.comps, a.comps)
    ia = np.flatnonzero(b.comps[np.minimum(at, len(b.comps) - 1)] == a.comps) if len(b.comps) else np.zeros(0, int)
    ib = at[ia]
    dense = (4 * (a.at[ia + 1] - a.at[ia]) >= len(a.ids)) & (4 * (b.at[ib + 1] - b.at[ib]) >= len(b.ids))
    if not dense.all():
        _sparse(a, b, ia[~dense], ib[~dense], lo)
    ca, cb = [a.column(i) for i in ia[dense]], [b.column(i) for i in ib[dense]]
    tmp = np.empty((STRIP, len(b.ids)))
    for s in range(0, len(a.ids), STRIP):
        part = lo[s : s + STRIP]
        for x, y in zip(ca, cb, strict=True):
            part += np.minimum(x[s : s + STRIP, None], y, out=tmp[: len(part)])
        yield s, part


def _agreements(a: Block, b: Block, s: int, upto: tuple[int, ...]):
    """Shares of equal hashes of a's rows from s on with all of b, after each of the numbers; 0 equals nothing."""
    x, y = a.sketch[:, s : s + STRIP], b.sketch
    x = np.where(x == 0, -1, x)
    n, same, out = np.zeros((x.shape[1], y.shape[1]), np.uint16), np.empty((x.shape[1], y.shape[1]), bool), {}
    for h in range(max(upto)):
        n += np.equal(x[h][:, None], y[h], out=same)
        if h + 1 in upto:
            out[h + 1] = n / (h + 1)
    return [out[k] for k in upto]


def _every(a, b, s, j, lo, ok):
    """Keep all pairs."""
    return np.nonzero(ok)


def near_levels(levels: tuple[float, ...], a, b, s, j, lo, ok):
    """Of a strip's pairs, those nearest to each level, with all that rounding to 9 places could make equal to them."""
    keep = np.zeros(j.shape, bool)
    if ok.any():
        for x in levels:
            d = np.where(ok, np.abs(j - x), np.inf)
            keep |= d <= d.min() + 4e-9
    return np.nonzero(keep & ok)


def best_of_row(a, b, s, j, lo, ok):
    """Of every row of a strip, the pairs with the largest similarity."""
    d = np.where(ok, j, -1.0)
    return np.nonzero(ok & (d == d.max(1, keepdims=True)))


def bucket_mates(rows: int, tables: int, tau: float, a, b, s, j, lo, ok):
    """Pairs of similarity tau or more that share a bucket: ``rows`` consecutive resolved hashes of one table."""
    ok = ok & (j >= tau)
    r, c = np.nonzero(ok)
    x, y = a.sketch[: rows * tables, s + r], b.sketch[: rows * tables, c]
    share = ((x == y) & (x != 0)).reshape(tables, rows, len(r)).all(1).any(0)
    return r[share], c[share]


def _share(rows: int, tables: int, a: Block, b: Block, s: int) -> np.ndarray:
    """Which of a's rows from s on share a bucket with which of b."""
    x = a.sketch[:, s : s + STRIP]
    share = np.zeros((x.shape[1], len(b.ids)), bool)
    for t in range(tables):
        same = np.ones(share.shape, bool)
        for h in range(t * rows, (t + 1) * rows):
            same &= (x[h][:, None] == b.sketch[h]) & (x[h] != 0)[:, None]
        share |= same
    return share


def best_candidates(rows: int, tables: int, top: int, a, b, s, j, lo, ok):
    """Of every row of a strip, what can be among its ``top`` most similar bucket mates (see ``bucket_mates``) when those whose
    similarity is equal to 9 places go by their ids: all that rounding could lift to the last one, and of equal ones the
    least ids."""
    share = _share(rows, tables, a, b, s)
    r, c = [], []
    for i in range(len(j)):
        own = np.flatnonzero(share[i])
        if len(own) > top:
            own = own[j[i, own] >= np.partition(j[i, own], -top)[-top] - 2e-9]
            own = own[np.lexsort((b.ids[own], j[i, own]))]
            at = np.arange(len(own))
            own = own[at - np.maximum.accumulate(np.where(np.diff(j[i, own], prepend=-1.0) > 0, at, 0)) < top]
        r.append(np.full(len(own), i))
        c.append(own)
    return np.concatenate(r), np.concatenate(c)


def _meet(batches, keep: Callable, upto: tuple[int, ...], both: bool, vectors: bool):
    last = {}
    for batch in batches:
        for ka, kb, da, db in zip(*(batch.column(i) for i in range(4)), strict=True):
            ka, kb = ka.as_py(), kb.as_py()
            if last.get("a", (None,))[0] != ka:
                last["a"] = ka, Block(da.as_py())
            a, b = last["a"][1], Block(db.as_py())
            got = []
            for s, lo in _minima(a, b) if vectors else ((s, None) for s in range(0, len(a.ids), STRIP)):
                e = slice(s, s + STRIP)
                if vectors:
                    j = lo / (a.l1[e, None] + b.l1 - lo)
                    ok = lo > 0
                else:
                    j = np.zeros((len(a.ids[e]), len(b.ids)))
                    ok = np.ones(j.shape, bool)
                if not both and ka == kb:
                    ok &= a.ids[e, None] < b.ids
                r, c = keep(a, b, s, j, lo, ok)
                cols = [a.ids[e][r], b.ids[c], j[r, c], a.l1[e][r], b.l1[c]]
                if not both and ka != kb:
                    swap = cols[0] > cols[1]
                    for x, y in ((0, 1), (3, 4)):
                        cols[x], cols[y] = np.where(swap, cols[y], cols[x]), np.where(swap, cols[x], cols[y])
                got.append(cols + [x[r, c] for x in (_agreements(a, b, s, upto) if upto else ())])
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*got, strict=True)], ["id_a", "id_b", "j", "l1_a", "l1_b", *(f"est_{k}" for k in upto)])


def _by_row(x: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Index of the component and weight of each entry, row by row, and where each row begins (n + 1)."""
    order = np.argsort(x.row, kind="stable")
    comp = np.repeat(np.arange(len(x.comps)), np.diff(x.at))[order]
    return comp, x.weight[order], np.searchsorted(x.row[order], np.arange(len(x.ids) + 1))


def _meet_mates(rows: int, tables: int, tau: float):
    """Over pairs of blocks: bucket mates whose norms don't exclude a similarity of tau, and of these alone the minima, as
    vectors of many components share some with nearly all."""

    def run(batches):
        last = {}
        for batch in batches:
            for ka, da, db in zip(*(batch.column(i) for i in (0, 2, 3)), strict=True):
                ka = ka.as_py()
                if last.get("a", (None,))[0] != ka:
                    a = Block(da.as_py())
                    last["a"] = ka, a, _by_row(a)
                _, a, (comp_a, weight_a, at_a) = last["a"]
                b = Block(db.as_py())
                comp_b, weight_b, at_b = _by_row(b)
                to = np.searchsorted(a.comps, b.comps)
                to[a.comps[np.minimum(to, len(a.comps) - 1)] != b.comps] = len(a.comps)
                to, dense, got = to[comp_b], np.zeros(len(a.comps) + 1), []
                for s in range(0, len(a.ids), STRIP):
                    l1 = a.l1[s : s + STRIP, None]
                    mates = _share(rows, tables, a, b, s) & (np.minimum(l1, b.l1) >= np.maximum(l1, b.l1) * tau * (1 - 1e-12))
                    for i in np.flatnonzero(mates.any(1)):
                        c = np.flatnonzero(mates[i])
                        own = slice(at_a[s + i], at_a[s + i + 1])
                        n = at_b[c + 1] - at_b[c]
                        head = np.cumsum(n) - n
                        e = np.arange(n.sum()) + np.repeat(at_b[c] - head, n)
                        dense[comp_a[own]] = weight_a[own]
                        lo = np.add.reduceat(np.minimum(dense[to[e]], weight_b[e]), head)
                        dense[comp_a[own]] = 0
                        j = lo / (a.l1[s + i] + b.l1[c] - lo)
                        c, j = c[j >= tau], j[j >= tau]
                        got.append([np.full(len(c), a.ids[s + i]), b.ids[c], j, np.full(len(c), a.l1[s + i]), b.l1[c]])
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*got, strict=True)], ["id_a", "id_b", "j", "l1_a", "l1_b"])

    return run


def _dense(x: Block, comps: np.ndarray, rows: int) -> np.ndarray:
    """Weights of the given components (all are the block's) x rows; rows beyond the block's are 0."""
    at = np.searchsorted(x.comps, comps)
    size = x.at[at + 1] - x.at[at]
    e = np.arange(size.sum()) + np.repeat(x.at[at] - (np.cumsum(size) - size), size)
    out = np.zeros((len(comps), rows))
    out[np.repeat(np.arange(len(comps)), size), x.row[e]] = x.weight[e]
    return out


def _rough(a: np.ndarray, b: np.ndarray, l1_a: np.ndarray, l1_b: np.ndarray):
    """Similarities of all pairs of two dense blocks of n columns, turn by turn: (turns, rows x n similarities), where row r has
    those of column i of ``a`` with i + r of ``b``; and by how much they may be off. Weights are rounded to whole numbers
    whose sums fit 16 bits, so that many are compared at once."""
    comps, n = a.shape
    most = max(l1_a.max(), l1_b.max())
    scale = (65535 - comps) / most
    some = min(np.count_nonzero(a, 0).max(), np.count_nonzero(b, 0).max())
    off = 2 * some / scale / (l1_a.min() + l1_b.min())  # the slope is at most 4 / (l1_a + l1_b) where all is shared
    off = off / max(1 - off / 2, 0.1) ** 2 + 1e-6
    x, y = (np.rint(w * scale).astype(np.uint16) for w in (a, b))
    y, l1_b = np.concatenate([y, y], 1), np.concatenate([l1_b, l1_b])
    l1_a, l1_b = (l1_a * scale).astype(np.float32), (l1_b * scale).astype(np.float32)

    def turns():
        tmp, lo = np.empty((comps, n), np.uint16), np.empty((STRIP, n), np.uint16)
        for s in range(0, n, STRIP):
            part = lo[: min(STRIP, n - s)]
            for r in range(len(part)):
                np.minimum(x, y[:, s + r : s + r + n], out=tmp)
                np.add.reduce(tmp, 0, dtype=np.uint16, out=part[r])
            j = part.astype(np.float32)
            rest = np.lib.stride_tricks.sliding_window_view(l1_b[s : s + len(part) + n - 1], n) + l1_a
            rest -= j
            j /= rest
            yield s, j

    return turns(), off


#: Cells into which similarities from 0 to 1 fall when those near a level are looked up.
CELLS = 8192
#: Off by more than this, rough similarities spare little.
ROUGH = 0.01


def meet_levels(levels: tuple[float, ...]):
    """Over pairs of blocks: the pairs nearest to each level (see ``near_levels``) of all that the task has seen. Where both
    blocks hold their components densely, rough similarities with a known error tell which pairs can be among them, and
    only these are computed exactly."""

    def run(batches):
        last, best = {}, np.full(len(levels), np.inf)

        def near(j):
            """Which of the similarities are as near to a level as any before."""
            keep = np.zeros(len(j), bool)
            for i, x in enumerate(levels):
                d = np.abs(j - x)
                best[i] = min(best[i], d.min(initial=np.inf))
                keep |= d <= best[i] + 4e-9
            return keep

        for batch in batches:
            for ka, kb, da, db in zip(*(batch.column(i) for i in range(4)), strict=True):
                ka, kb = ka.as_py(), kb.as_py()
                if last.get("a", (None,))[0] != ka:
                    last["a"] = ka, Block(da.as_py())
                a, b = last["a"][1], Block(db.as_py())
                comps = np.intersect1d(a.comps, b.comps, assume_unique=True)
                if not len(comps):
                    continue
                n, got, rough = max(len(a.ids), len(b.ids)), [], None
                if 2 * len(comps) * n <= 8 * (len(a.row) + len(b.row)):
                    x, y = _dense(a, comps, n), _dense(b, comps, n)
                    pad = [np.concatenate([z.l1, np.full(n - len(z.ids), z.l1.max())]) for z in (a, b)]
                    rough, off = _rough(x, y, *pad)
                if rough is None or off > ROUGH:
                    found = ((*np.nonzero(lo > 0), s, lo) for s, lo in _minima(a, b))
                    found = ((s + r, c, lo[r, c]) for r, c, s, lo in found)
                else:
                    x, y = x.T.copy(), y.T.copy()
                    found = _exact(x, y, rough, off, levels, best, len(a.ids), len(b.ids))
                for r, c, lo in found:
                    ok = lo > 0
                    if ka == kb:
                        ok &= a.ids[r] < b.ids[c]
                    r, c, lo = r[ok], c[ok], lo[ok]
                    j = lo / (a.l1[r] + b.l1[c] - lo)
                    keep = near(j)
                    r, c, j = r[keep], c[keep], j[keep]
                    swap = a.ids[r] > b.ids[c]
                    first, second = (np.where(swap, p, q) for p, q in ((b.ids[c], a.ids[r]), (a.ids[r], b.ids[c])))
                    got.append([first, second, j, np.where(swap, b.l1[c], a.l1[r]), np.where(swap, a.l1[r], b.l1[c])])
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*got, strict=True)], ["id_a", "id_b", "j", "l1_a", "l1_b"])

    return run


def _exact(x: np.ndarray, y: np.ndarray, rough, off: float, levels: tuple[float, ...], best: np.ndarray, rows_a: int, rows_b: int):
    """(row of a, row of b, sum of minima) of the pairs whose rough similarity lets them be as near to a level as ``best``,
    which the caller lowers meanwhile."""
    edge = np.arange(CELLS + 1) / CELLS
    for s, j in rough:
        table = np.zeros(CELLS + 2, bool)
        for level, d in zip(levels, best, strict=True):
            table[1:-1] |= (edge[1:] >= level - d - off - 1e-8) & (edge[:-1] <= level + d + off + 1e-8)
        table[0], table[-1] = table[1], table[-2]
        j *= CELLS
        cell = j.astype(np.int32)
        cell += 1
        t, r = np.nonzero(table.take(cell, mode="clip"))
        c = (r + t + s) % len(y)
        inside = (r < rows_a) & (c < rows_b)
        r, c = r[inside], c[inside]
        yield r, c, np.concatenate([np.zeros(0), *(np.minimum(x[r[e]], y[c[e]]).sum(1) for e in (slice(at, at + STRIP) for at in range(0, len(r), STRIP)))])


def _blocks(v: DataFrame | None, sketches: DataFrame | None) -> tuple[DataFrame, int, int]:
    """Blocks (block, data), how many, and how many partitions they go to."""
    kind = "array<int>" if sketches is None else sketches.schema["sketch"].dataType.simpleString()
    if v is None:
        p = sketches.select("vec_id", F.array().cast("array<long>").alias("comps"), F.array().cast("array<double>").alias("weights"), "sketch")
    else:
        got = v.groupBy("vec_id").agg(F.collect_list(F.struct("comp", "weight")).alias("e"))
        p = got.select("vec_id", F.col("e.comp").cast("array<long>").alias("comps"), F.col("e.weight").cast("array<double>").alias("weights"))
        p = p.join(sketches.select("vec_id", "sketch"), "vec_id") if sketches is not None else p.withColumn("sketch", F.array().cast("array<int>"))
    p = materialize(p.select(F.col("vec_id").cast("long").alias("vec_id"), F.size("comps").alias("d"), "comps", "weights", F.col("sketch").cast(kind).alias("sketch")))
    n, size = p.agg(F.count("*"), F.coalesce(F.sum(F.col("d") * 20 + F.size("sketch") * (8 if "big" in kind else 4) + 16), F.lit(0))).first()
    count = max(1, -(-n // ROWS), -(-size // BYTES))
    p = p.select(F.pmod(F.xxhash64("vec_id"), F.lit(count)).cast("int").alias("block"), "*")
    return materialize(p.groupBy("block").applyInArrow(_pack_block, "block int, data binary")), count, min(count, max(PARTS, -(-size // PART_BYTES)))


def pairs(v: DataFrame | None, sketches: DataFrame | None = None, upto: tuple[int, ...] = (), keep: Callable = _every, against: DataFrame | None = None, against_sketches: DataFrame | None = None, run: Callable | None = None) -> DataFrame:
    """id_a, id_b, j, l1_a, l1_b, est_<k> for each k of ``upto``: all pairs a < b of ``v`` that share a component, with their
    similarity and the share of their first k hashes that agree; of ``v`` and ``against`` (whose sketches are
    ``against_sketches``), if that is given; without ``v``, all pairs of the sketches. ``keep`` may pick from a strip's pairs before they leave the task, ``run`` may do all of it."""
    left, count, parts = _blocks(v, sketches)
    right, _, parts_b = (left, count, parts) if against is None else _blocks(against, against_sketches)
    a, b = (x.select(F.col("block").alias(f"k_{s}"), F.col("data").alias(f"d_{s}")) for x, s in ((left, "a"), (right, "b")))
    j = a.repartitionByRange(parts, "k_a").crossJoin(b.repartitionByRange(parts_b, "k_b")).select("k_a", "k_b", "d_a", "d_b")
    if against is None:  # each block meets the half of the others that follows it, in a ring
        step = F.pmod(F.col("k_b") - F.col("k_a"), F.lit(count))
        j = j.where((step * 2 < count) | ((step * 2 == count) & (F.col("k_a") < F.col("k_b"))))
    run = run or partial(_meet, keep=keep, upto=tuple(upto), both=against is not None, vectors=v is not None)
    out = j.mapInArrow(run, ", ".join([PAIR, *(f"est_{k} double" for k in upto)]))
    kind = (sketches if v is None else v).schema["vec_id"].dataType
    kind_b = kind if against is None else against.schema["vec_id"].dataType
    return out.select(F.col("id_a").cast(kind).alias("id_a"), F.col("id_b").cast(kind_b).alias("id_b"), *out.columns[2:])


def mates(v: DataFrame, sketches: DataFrame, against: DataFrame, against_sketches: DataFrame, rows: int, tables: int, tau: float) -> DataFrame:
    """id_a, id_b, j, l1_a, l1_b: pairs of the two sides that share a bucket (see ``bucket_mates``) and have a similarity of
    tau or more, tau above 0."""
    return pairs(v, sketches, against=against, against_sketches=against_sketches, run=_meet_mates(rows, tables, tau))
