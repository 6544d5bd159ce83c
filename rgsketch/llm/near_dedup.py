"""Near-duplicate groups by SetSketch registers.

A document is the set of its distinct word shingles (64-bit hashes). Register j of its sketch keeps the smallest of its
elements' exponential variates on a logarithmic scale, floor(1 - log_b(min)), truncated to 0 .. q + 1; registers merge by
maximum and agree with a probability that follows the Jaccard similarity. Documents of one set form a class, and one sketch
a class is banded. Every class of a band bucket is compared with the bucket's hub, the class that shares most buckets (the
text that copies were made from, as a rule). The joint likelihood of the registers (greater, less, equal), given both exact
set sizes, spares the pairs that six standard deviations exclude; the rest is confirmed on the full sets in whole numbers.

Two classes of a bucket that both stand off its hub may still be linked. Such a link needs shared differences from the hub:
with a and b elements in which they differ from it, at least (a + b - (1 - t) / t * the smaller set) / 2 must be common for
a similarity of t. So the differences are joined, each class giving only a prefix (what it adds, then what it lacks) long
enough that every link meets in one element; pairs so found are confirmed too. No candidate pair is dropped and no pairs of
a whole group are made.

Edge cases: a text with fewer words than a shingle is one shingle of all its words; a null or wordless text has the empty
set and is linked with nothing; repeated rows and equal texts share a class; null ids never become a component's id unless
no other is there (then the id is null and the rows count as kept); an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.llm.common import bit_filter, chunks, filter_spot, in_filter, materialize, mix64, row_slices, shingle_hashes, utf8, word_hashes
from rgsketch.llm.graph import components

BASE, RATE, TOP = 1.001, 20.0, (1 << 16) - 2
ROWS = 6
MISS = 1e-6
_RNG = np.random.default_rng(71)
_MULT = _RNG.integers(0, 1 << 31, 4096, dtype=np.uint32) * np.uint32(2) + np.uint32(1)


def row_key(text: F.Column, id_: F.Column) -> F.Column:
    """A row's key by text and id; a null counts as a value of its own."""
    text = text.cast("string")
    return F.xxhash64(text, text.isNull(), id_, id_.isNull())


def bands_for(threshold: float, rows: int = ROWS, miss: float = MISS) -> int:
    """Bands that miss a pair at the threshold with probability ``miss`` at most."""
    return math.ceil(math.log(miss) / math.log(1 - threshold**rows))


def shingle_sets(texts: pa.Array, width: int):
    """Yields (lo, hi, sets): the sorted distinct shingle hashes of each of rows lo .. hi - 1."""
    raw, offsets = utf8(texts)
    for lo, hi in chunks(offsets):
        h, _, _, row = word_hashes(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
        all_ = shingle_hashes(h, width)
        out = []
        for a, b in zip(row[:-1].tolist(), row[1:].tolist(), strict=True):
            if b - a >= width:
                out.append(np.unique(all_[a : b - width + 1]))
            elif b > a:
                out.append(mix64(shingle_hashes(h[a:b], b - a) + np.uint64(b - a)))
            else:
                out.append(np.zeros(0, np.uint64))
        yield lo, hi, out


def registers(sets: list[np.ndarray], m: int) -> np.ndarray:
    """len(sets) x m registers (uint16) of non-empty sets."""
    flat = np.concatenate(sets)
    start = np.cumsum([0, *map(len, sets[:-1])])
    word = (mix64(flat) >> np.uint64(32)).astype(np.uint32)
    least = np.empty((m, len(sets)), np.uint32)
    for j in range(m):
        v = word * _MULT[j]
        v ^= v >> np.uint32(16)
        v *= _MULT[4095 - j]
        least[j] = np.minimum.reduceat(v, start)
    x = -np.log1p(-(least.T.astype(np.float64) + 0.5) / 2.0**32) / RATE
    return np.clip(np.floor(1 - np.log(x) / math.log(BASE)), 0, TOP + 1).astype(np.uint16)


def _sketch(width: int, m: int):
    def run(batches):
        for batch in batches:
            n = np.zeros(batch.num_rows, np.int64)
            cls: list = [None] * batch.num_rows
            regs: list = [None] * batch.num_rows
            for lo, hi, sets in shingle_sets(batch.column(2), width):
                n[lo:hi] = [len(s) for s in sets]
                full = [i for i, s in enumerate(sets) if len(s)]
                if full:
                    own = [sets[i] for i in full]
                    for i, r in zip(full, registers(own, m), strict=True):
                        regs[lo + i] = r.astype(">u2").tobytes()
                        s = sets[i]
                        cls[lo + i] = int(mix64(s).sum()).to_bytes(8, "big") + int(mix64(s ^ np.uint64(0x5BD1E995)).sum()).to_bytes(8, "big")
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n), pa.array(cls, pa.binary()), pa.array(regs, pa.binary())], ["doc_id", "rk", "n", "cls", "regs"])

    return run


def _p(x):
    return -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / math.log(BASE)


def joint_estimate(more: np.ndarray, less: np.ndarray, same: np.ndarray, na: np.ndarray, nb: np.ndarray, threshold: float, grid: int = 100):
    """Likeliest Jaccard similarity, the largest one within six standard deviations, from register comparisons."""
    u = (na / (na + nb))[:, None]
    v = 1 - u
    j = np.linspace(0, 1, grid + 1)[None, :] * np.minimum(u / v, v / u)
    up, down = np.maximum(_p(u - v * j), 1e-12), np.maximum(_p(v - u * j), 1e-12)
    like = more[:, None] * np.log(up) + less[:, None] * np.log(down) + same[:, None] * np.log(np.maximum(1 - up - down, 1e-12))
    best = like.argmax(1)
    r = np.arange(len(j))
    possible = like >= like[r, best][:, None] - 18.0
    return j[r, best], np.where(possible, j, 0).max(1)


def _bound(threshold: float):
    """Add j_max, an upper bound of the similarity, to candidate pairs with both sides' registers."""

    def run(batches):
        for batch in row_slices(batches):
            a, b, ra, rb, na, nb = batch.columns
            x, y = (np.frombuffer(b"".join(c.to_pylist()), ">u2").reshape(batch.num_rows, -1) for c in (ra, rb))
            more, less = (x > y).sum(1), (x < y).sum(1)
            _, top = joint_estimate(more, less, x.shape[1] - more - less, na.to_numpy().astype(float), nb.to_numpy().astype(float), threshold)
            yield pa.RecordBatch.from_arrays([a, b, na, nb, pa.array(top)], ["a", "b", "na", "nb", "j_max"])

    return run


def _confirm(batches):
    for batch in row_slices(batches):
        out = [len(np.intersect1d(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), assume_unique=True)) for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.int64())], ["a", "b", "common"])


def _differences(percent: int):
    """From each (hub, class) with both sets, the class's elements of the symmetric difference that a link off the hub may
    have to show, with their place in it (from 0)."""
    slack = (100 - percent) / percent

    def run(batches):
        for batch in row_slices(batches):
            out: list[tuple] = []
            for hub, cls, root, off, x, y in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                mine = np.concatenate([np.setdiff1d(y, x, assume_unique=True), np.setdiff1d(x, y, assume_unique=True)])
                least = (1 - percent / 100) * max(len(x), percent / 100 * len(y))  # what a class off the hub differs in at least
                # two of them off the hub, or one that is and one that differs in no fewer elements than they share
                need = max(1, math.ceil((len(mine) - slack * len(y) if off else (least + len(mine) - slack * len(y)) / 2) - 1e-9))
                items = mine[: max(0, len(mine) - need + 1)].astype(np.int64).tolist()
                out += [(hub, cls, root, off, len(y), len(mine), v, i) for i, v in enumerate(items)]
                if len(out) > 50_000:
                    yield _rows(out)
                    out = []
            if out:
                yield _rows(out)

    return run


def _rows(out: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.binary(), pa.binary(), pa.binary(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int32()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], ["hub", "cls", "root", "off", "n", "size", "item", "place"])


class NearDuplicates:
    """Links of 100 * |intersection| >= percent * |union| between the sets of width-word shingles."""

    def __init__(self, df: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text"):
        self.width, self.percent, self.threshold = width, percent, percent / 100
        self.bands = bands_for(self.threshold)
        self.m = self.bands * ROWS
        text = df[text_col].cast("string")
        self.rows = df.select(df[id_col].cast("long").alias("doc_id"), row_key(df[text_col], df[id_col]).alias("rk"), text.alias("text"))
        kind = "doc_id long, rk long, n long, cls binary, regs binary"
        self.sketches = materialize(self.rows.mapInArrow(_sketch(width, self.m), kind))
        some = self.sketches.where("cls IS NOT NULL").groupBy("cls").agg(F.min("doc_id").alias("rep"), F.min("rk").alias("rk"), F.max("n").alias("n"))
        regs = self.sketches.select("cls", "rk", "regs").where("cls IS NOT NULL")
        self.classes = materialize(some.join(regs.dropDuplicates(["cls", "rk"]), ["cls", "rk"]).select("cls", "rep", "rk", "n", "regs"))

    def _candidates(self) -> DataFrame:
        """(bucket, hub, cls, n, n_hub, members) of the classes beside the hub in buckets of two classes or more."""
        parts = F.transform(F.sequence(F.lit(0), F.lit(self.bands - 1)), lambda i: F.xxhash64(i, F.col("regs").substr(i * (2 * ROWS) + 1, F.lit(2 * ROWS))))
        rows = self.classes.select("cls", "n", F.explode(parts).alias("bucket"))
        full = rows.groupBy("bucket").agg(F.count("*").alias("members")).where("members > 1")
        rows = materialize(rows.join(full, "bucket"))
        shared = rows.groupBy("cls").agg(F.sum("members").alias("shared"))
        hubs = rows.join(shared, "cls").groupBy("bucket").agg(F.max(F.struct("shared", "cls", "n")).alias("hub"))
        got = rows.join(hubs.select("bucket", F.col("hub.cls").alias("hub"), F.col("hub.n").alias("n_hub")), "bucket")
        return materialize(got.where("cls <> hub"))

    def _close(self, a: str, b: str) -> F.Column:
        return F.least(a, b) * 100 >= F.greatest(a, b) * self.percent

    def _verify(self, pairs: DataFrame) -> DataFrame:
        """(a, b, na, nb, j_max, common) of distinct pairs; common is null where j_max is below the threshold."""
        side = self.classes.select("cls", "regs", "rk")
        full = pairs.join(side.select(F.col("cls").alias("a"), F.col("regs").alias("ra")), "a").join(side.select(F.col("cls").alias("b"), F.col("regs").alias("rb")), "b")
        bound = materialize(full.select("a", "b", "ra", "rb", "na", "nb").mapInArrow(_bound(self.threshold), "a binary, b binary, na long, nb long, j_max double"))
        near = bound.where(F.col("j_max") >= self.threshold)
        ends = near.select(F.col("a").alias("cls")).unionByName(near.select(F.col("b").alias("cls"))).distinct()
        sets = self._sets_of(ends)
        both = near.select("a", "b").join(sets.select(F.col("cls").alias("a"), F.col("items").alias("x")), "a").join(sets.select(F.col("cls").alias("b"), F.col("items").alias("y")), "b")
        common = both.select("a", "b", "x", "y").mapInArrow(_confirm, "a binary, b binary, common long")
        return materialize(bound.join(common, ["a", "b"], "left"))

    def _sets_of(self, ends: DataFrame) -> DataFrame:
        """(cls, items) of the given classes, from one row each."""
        wanted = materialize(ends.join(self.classes.select("cls", "rk"), "cls"))
        return materialize(self._sets(wanted).join(wanted, "rk").dropDuplicates(["cls"]).select("cls", "items"))

    def _sets(self, wanted: DataFrame) -> DataFrame:
        """(rk, items) of the rows that a fixed-size bit filter of the wanted row keys lets pass."""
        table = bit_filter(wanted, "rk")
        width = self.width

        def run(batches):
            for batch in batches:
                s = batch.column(2).to_numpy()
                go = np.flatnonzero(in_filter(table, s))
                if len(go):
                    own = batch.take(pa.array(go))
                    items = [x.tobytes() for _, _, sets in shingle_sets(own.column(1), width) for x in sets]
                    yield pa.RecordBatch.from_arrays([own.column(0), pa.array(items, pa.binary())], ["rk", "items"])

        return self.rows.select("rk", "text", filter_spot("rk").alias("spot")).mapInArrow(run, "rk long, items binary")

    def links(self) -> DataFrame:
        """Confirmed (a, b) between classes, enough of them to span every component of all links."""
        cand = self._candidates()
        stars = cand.where(self._close("n", "n_hub")).select(F.col("hub").alias("a"), F.col("cls").alias("b"), F.col("n_hub").alias("na"), F.col("n").alias("nb")).distinct()
        linked = F.col("common") * 100 >= (F.col("na") + F.col("nb") - F.col("common")) * self.percent
        edges = materialize(self._verify(stars).where(linked).select("a", "b"))
        roots = components(edges)
        own = roots.select(F.col("node").alias("cls"), "root")
        lead = roots.select(F.col("node").alias("hub"), F.col("root").alias("root_hub"))
        table = cand.where("members > 2").join(own, "cls", "left").join(lead, "hub", "left")
        table = table.select("bucket", "hub", "cls", F.coalesce("root", "cls").alias("root"), (F.coalesce("root", "cls") != F.coalesce("root_hub", "hub")).alias("off"))
        table = materialize(table)
        some = table.groupBy("bucket").agg(F.max("off").alias("any")).where("any").select("bucket")  # elsewhere all are joined
        pairs = materialize(table.join(some, "bucket").select("hub", "cls", "root", "off").distinct())
        sets = self._sets_of(pairs.select("cls").unionByName(pairs.select(F.col("hub").alias("cls"))).distinct())
        both = pairs.join(sets.select(F.col("cls").alias("hub"), F.col("items").alias("x")), "hub").join(sets.select("cls", F.col("items").alias("y")), "cls")
        kind = "hub binary, cls binary, root binary, off boolean, n long, size long, item long, place int"
        diff = materialize(both.select("hub", "cls", "root", "off", "x", "y").mapInArrow(_differences(self.percent), kind))
        # classes of one root are joined already: elements that only they show make no pairs, however many classes they are
        parts = diff.groupBy("hub", "item").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.max("off").alias("any"))
        diff = materialize(diff.join(parts.where("any AND lo <> hi").select("hub", "item"), ["hub", "item"]))
        x = diff.where("off").select("hub", "item", *[F.col(c).alias(f"{c}_x") for c in ("cls", "root", "n", "size", "place")])
        y = diff.select("hub", "item", *[F.col(c).alias(f"{c}_y") for c in ("cls", "root", "off", "n", "size", "place")])
        need = F.greatest(F.lit(1), F.ceil((F.col("size_x") + F.col("size_y") - F.least("n_x", "n_y") * (100 - self.percent) / self.percent) / 2 - 1e-9))
        fits = (F.col("place_x") <= F.col("size_x") - need) & (F.col("place_y") <= F.col("size_y") - need)
        once = ~F.col("off_y") | (F.col("cls_x") < F.col("cls_y"))
        rest = x.join(y, ["hub", "item"]).where((F.col("root_x") != F.col("root_y")) & self._close("n_x", "n_y") & fits & once)
        ends = [F.struct(F.col(f"cls_{k}").alias("cls"), F.col(f"n_{k}").alias("n")) for k in "xy"]
        rest = rest.select(F.least(*ends).alias("lo"), F.greatest(*ends).alias("hi")).distinct().select(F.col("lo.cls").alias("a"), F.col("hi.cls").alias("b"), F.col("lo.n").alias("na"), F.col("hi.n").alias("nb"))
        rest = materialize(rest)
        if rest.isEmpty():
            return edges
        return materialize(edges.unionByName(self._verify(rest).where(linked).select("a", "b")))

    def _members(self) -> DataFrame:
        """doc_id, rk, n, root (null without words) and component_id of every row."""
        roots = components(self.links())
        named = self.classes.select("cls", "rep").join(roots.select(F.col("node").alias("cls"), "root"), "cls", "left").withColumn("root", F.coalesce("root", "cls"))
        ids = named.groupBy("root").agg(F.min("rep").alias("component_id"))
        return self.sketches.select("doc_id", "rk", "n", "cls").join(named.join(ids, "root").select("cls", "root", "component_id"), "cls", "left")

    def groups(self) -> DataFrame:
        """doc_id, n_shingles, component_id, kept for every row."""
        comp = F.when(F.col("root").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
        return self._members().select("doc_id", F.col("n").alias("n_shingles"), comp.alias("component_id"), comp.eqNullSafe(F.col("doc_id")).alias("kept"))

    def survivors(self) -> DataFrame:
        """(rk, doc_id) of one row of each group, the smallest id (null last), and of every different row without words."""
        rows = self._members()
        least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "rk")).alias("r")
        grouped = rows.where("root IS NOT NULL").groupBy("root").agg(least).select("r.rk", "r.doc_id")
        return grouped.unionByName(self.sketches.where("cls IS NULL").select("rk", "doc_id").distinct())


def query(spark, sf_dir: str) -> DataFrame:
    return NearDuplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), width=3, percent=85).groups()


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """One row of each group stays, with its columns; rows without words stay (repeated rows once).

    Rows are known by id and text together, so that rows of one id (or of none) with different texts stay apart.
    """
    stay = NearDuplicates(docs, width, percent).survivors().select(F.col("rk").alias("__stay"), F.col("doc_id").alias("__of"))
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("rec"), row_key(docs["text"], docs["doc_id"]).alias("__rk"), docs["doc_id"].cast("long").alias("__id"))
    same = (F.col("__rk") == F.col("__stay")) & F.col("__id").eqNullSafe(F.col("__of"))
    return rows.join(stay, same, "left_semi").dropDuplicates(["__rk", "__id"]).select("rec.*")


ORACLE = r"""
WITH t AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))) END) AS g FROM t),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
e AS (SELECT a, b FROM links UNION SELECT b, a FROM links)
SELECT t.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(t.doc_id, coalesce(r.r, t.doc_id)) AS component_id, t.doc_id = least(t.doc_id, coalesce(r.r, t.doc_id)) AS kept
FROM t LEFT JOIN n USING (doc_id) LEFT JOIN (
  WITH RECURSIVE walk(x, r) AS (SELECT a, b FROM e UNION SELECT w.x, e.b FROM walk w JOIN e ON e.a = w.r)
  SELECT x, min(r) AS r FROM walk GROUP BY x) r ON r.x = t.doc_id
"""
