"""Benchmark decontamination by a random-walk embedding and bit sampling.

Texts are lower-cased with single blanks. The embedding walks along a string: step j emits the current byte and moves on
when a random function of (j, byte) says so; strings at small edit distance agree in most of 3n places. For every window
of an item's length the embedding is read at sampled places only; equal samples in one of ``tables`` repetitions make a
candidate if all sampled places together agree as the distance allows, and ``tables`` follows from the target recall.
Candidates are confirmed by exact edit distance (bit-parallel,
free ends in the document): at most (1 - similarity) of the item's bytes may differ.

Windows are laid where a document holds a run of whole words of an item, of ``RUN_BYTES`` bytes or the least number of
words that reach them, at the place that puts this run where the item has it. Items of which no such run survives are found
exactly: an item that may take e edits is cut into an even number of pieces above e, so some two neighbouring pieces share
one edit at most and one of the two stands unchanged. Places of unchanged pieces are looked up, the neighbour is compared
with one edit allowed, then a group of such pairs with less edits than it has pieces, and at last the item. Every step
keeps all that lies within the limit, so nothing is lost. The benchmark is a stated query set: it is taken in blocks of ``block_bytes``, each sent
with the code of one pass, so that what is sent has a bound.

Edge cases: null and empty texts and items match nothing; items shorter than ``RUN_BYTES``
have no run and match nothing; very long texts are read whole; repeated rows, texts and items give
repeated pairs once each, also where an id is null; empty tables give empty results.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.llm.common import chunks, prefix_hash, row_slices, span_hash, utf8, words

SIMILARITY = 0.8
RECALL = 0.99
SAMPLES = 3
#: Share of embedded places that agree for a pair at the limit; with RECALL it sets the number of tables.
AGREE = 0.3
#: A window whose sampled places agree less isn't verified. Measured over 60 items: at the limit (20 % edits) half agree in
#: 0.31 of the places, 99 of 100 in 0.196 or more, all in 0.17; text without relation in 0.176 at most, 0.161 by 95 of 100.
LEAST_AGREE = 0.19
RUN_BYTES = 9
#: Bytes of a piece that are looked up, of its neighbour that are compared, and of a group of pairs.
KEY_BYTES = 8
MATE_BYTES = 7
GROUP_BYTES = 32
#: Places whose pieces are compared at once.
PLACES = 20_000
#: Random walks; each is sampled tables / WALKS times.
WALKS = 8
BLOCK_BYTES = 4 << 20
#: Windows that are embedded at once.
WINDOWS = 20_000
_MAP_BITS = 22


def tables_for(recall: float = RECALL, samples: int = SAMPLES, agree: float = AGREE) -> int:
    return math.ceil(math.log(1 - recall) / math.log(1 - agree**samples))


def normalise(text: str | None) -> str:
    return " ".join((text or "").lower().split())


def embed(raw: np.ndarray, start: np.ndarray, end: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """steps x windows: the byte that each walk over raw[start:end] emits at each step; 0 past an end.

    moves is steps x 256 of 0 and 1, and 0 for byte 0, which only stands past an end.
    """
    n, wide = len(start), int((end - start).max(initial=0)) + 1
    own = np.zeros((n, wide), np.uint8)
    inside = np.arange(wide) < (end - start)[:, None]
    own[inside] = raw[(start[:, None] + np.arange(wide))[inside]]
    own, at = own.ravel(), np.arange(n, dtype=np.int64) * wide
    steps = min(len(moves), 2 * wide)
    out = np.zeros((len(moves), n), np.uint8)
    for j in range(steps):
        byte = own[at]
        out[j] = byte
        at += moves[j][byte]
    return out


def edits(item: bytes, text: bytes, limit: int) -> int:
    """Least edit distance of the item to any part of the text; anything above limit may come back as limit + 1."""
    return min(_best(item, text)[0], limit + 1)


def _best(item: bytes, text: bytes) -> tuple[int, int]:
    """Least edit distance of the item to any part of the text, and where the first such part ends."""
    m, end = len(item), 0
    peq: dict[int, int] = {}
    for i, c in enumerate(item):
        peq[c] = peq.get(c, 0) | 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    pv, mv, score, best = full, 0, m, m
    for k, c in enumerate(text, 1):
        eq = peq.get(c, 0)
        xv = eq | mv
        xh = (((eq & pv) + pv) ^ pv) | eq
        ph = mv | (~(xh | pv) & full)
        mh = pv & xh
        if ph & top:
            score += 1
        elif mh & top:
            score -= 1
        ph = ph << 1 & full
        mh = mh << 1 & full
        pv = mh | (~(xv | ph) & full)
        mv = ph & xv
        if score < best:
            best, end = score, k
    return best, end


def trigrams(raw: np.ndarray) -> np.ndarray:
    """Counts of hashed byte trigrams; an edit takes three of them away at most."""
    x = raw.astype(np.uint32)
    return np.bincount(((x[:-2] * np.uint32(961) + x[1:-1] * np.uint32(31) + x[2:]) * np.uint32(0x9E3779B1)) >> np.uint32(20), minlength=4096)


@dataclass
class Pieces:
    """Pieces of the items, ordered by the bucket of their key (their first KEY_BYTES bytes at most)."""

    keys: dict[int, tuple[np.ndarray, int]]  # length of key: first piece of each bucket, bits of the bucket's number
    item: np.ndarray
    at: np.ndarray  # first byte of the piece in its item
    key: np.ndarray
    mate: np.ndarray  # up to 8 bytes of the neighbour, counted away from the piece
    mask: np.ndarray  # which bytes of mate count
    before: np.ndarray  # the neighbour stands before the piece
    step: np.ndarray  # bytes from the piece's first byte to the neighbour's near end
    group: np.ndarray
    group_at: np.ndarray  # first byte of each group in its item
    group_bytes: np.ndarray
    group_edits: np.ndarray
    group_eq: np.ndarray  # groups x 256: where each byte stands in the group


@dataclass
class Index:
    """One block of the benchmark: seeds of word runs and the sampled embeddings of its items."""

    ids: list[int | None]
    items: list[bytes]
    seeds: np.ndarray  # sorted hashes of runs
    seed_item: np.ndarray
    seed_at: np.ndarray  # byte offset of the run in its item
    mask: np.ndarray  # bit table of seeds, tested first
    walks: list[np.ndarray]  # moves of each walk
    places: list[np.ndarray]  # tables x items x samples, of each walk
    sampled: list[np.ndarray]  # the items' bytes there
    pieces: Pieces


def runs(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first byte and row of the shortest run of whole words of RUN_BYTES or more from each word on, within its row."""
    start, end, row = words(raw, offsets)
    last = np.searchsorted(end, start + RUN_BYTES)
    of = np.repeat(np.arange(len(offsets) - 1), np.diff(row))
    ok = np.flatnonzero(last < row[of + 1])
    start, of = start[ok], of[ok]
    return span_hash(prefix_hash(raw), start, end[last[ok]]), start, of


def limit_of(item: bytes, similarity: float) -> int:
    return int(len(item) * (1 - similarity) + 1e-9)


def _code(part: bytes) -> int:
    return int.from_bytes(part[:8], "little")


def _bucket(key: np.ndarray, bits: int) -> np.ndarray:
    return ((key * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits)).astype(np.int64)


def cut(items: list[bytes], similarity: float) -> Pieces:
    """The pieces of every item, their neighbours and the groups of pairs."""
    rows, groups = [], []
    for i, item in enumerate(items):
        m, n = len(item), limit_of(item, similarity) + 1
        n = min(n + n % 2, m - m % 2)
        if m < RUN_BYTES:
            continue
        ends = [j * m // n for j in range(n + 1)]
        size = max(1, GROUP_BYTES * n // (2 * m))
        firsts = [j * (n // 2) // -(-n // 2 // size) * 2 for j in range(-(-n // 2 // size))] + [n]
        for lo, hi in zip(firsts, firsts[1:], strict=False):
            whole = item[ends[lo] : ends[hi]][:64]
            for j in range(lo, hi):
                a, b = ends[j], ends[j + 1]
                if j % 2:
                    mate, before, step = item[ends[j - 1] : a][::-1][:MATE_BYTES], True, 0
                else:
                    mate, before, step = item[b : ends[j + 2]][:MATE_BYTES], False, b - a
                rows.append((min(b - a, KEY_BYTES), i, a, _code(item[a : min(b, a + KEY_BYTES)]), _code(mate), (1 << 8 * len(mate)) - 1, before, step, len(groups)))
            groups.append((ends[lo], whole, hi - lo - 1))
    kind = [np.int64, np.int64, np.int64, np.uint64, np.uint64, np.uint64, bool, np.int64, np.int64]
    length, item, at, key, mate, mask, before, step, group = (np.array([r[k] for r in rows], t) for k, t in enumerate(kind))
    bits = min(22, max(8, len(rows).bit_length() + 4))
    order = np.lexsort((_bucket(key, bits), length))
    keys = {}
    for size in np.unique(length).tolist():
        base = np.searchsorted(length[order], size)
        spot = _bucket(key[order][length[order] == size], bits)
        keys[size] = (base + np.searchsorted(spot, np.arange((1 << bits) + 1)), bits)
    eq = np.zeros((len(groups), 256), np.uint64)
    for g, (_, whole, _) in enumerate(groups):
        for k, c in enumerate(whole):
            eq[g, c] |= np.uint64(1 << k)
    tail = [np.array([f(g) for g in groups], np.int64) for f in (lambda g: g[0], lambda g: len(g[1]), lambda g: g[2])]
    return Pieces(keys, *(x[order] for x in (item, at, key, mate, mask, before, step, group)), *tail, eq)


def near_mates(doc: np.ndarray, mate: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """Whether bytes that begin doc are within one edit of mate; some more pass, none less."""
    one, byte = np.uint64(1), np.uint64(8)
    x = (doc ^ mate) & mask
    low = x & (~x + one)
    rest = ~low + one
    ok = (x & (~(low << byte) + one)) == 0
    ok |= (((doc >> byte) ^ mate) & mask & rest) == 0  # an added byte
    ok |= ((doc ^ (mate >> byte)) & (mask >> byte) & rest) == 0  # a missing byte
    return ok


def near_groups(p: Pieces, group: np.ndarray, raw: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Whether some part of raw[lo:hi] lies within the edits of the group: the bit-parallel steps of ``edits`` over all rows at once."""
    one = np.uint64(1)
    size, limit, flat = p.group_bytes[group], p.group_edits[group], p.group_eq.ravel()
    last, base = (size - 1).astype(np.uint64), group * 256
    pv, mv = np.full(len(group), ~np.uint64(0)), np.zeros(len(group), np.uint64)
    score, ok = size.copy(), size <= limit
    for k in range(int((hi - lo).max(initial=0))):
        at = lo + k
        inside = at < hi
        eq = np.where(inside, flat[base + raw[np.where(inside, at, 0)]], np.uint64(0))
        xv = eq | mv
        xh = (((eq & pv) + pv) ^ pv) | eq
        ph = mv | ~(xh | pv)
        mh = pv & xh
        score += ((ph >> last) & one).astype(np.int64) - ((mh >> last) & one).astype(np.int64)
        ph, mh = ph << one, mh << one
        pv = mh | ~(xv | ph)
        mv = ph & xv
        ok |= (score <= limit) & inside
    return ok


def piece_hits(p: Pieces, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Columns row, item and first byte that the item would have there, of the places where a group of pairs fits."""
    none = np.zeros((0, 3), np.int64)
    if not len(p.item) or not len(raw):
        return none
    wide = np.zeros(len(raw) + 16, np.uint8)
    wide[8:-8] = raw
    n = len(raw) + 1 + int(p.step.max())
    wide = np.pad(wide, (0, n - len(raw)))
    # the eight bytes from a place on, and those before it, nearest first
    after, before = np.ndarray((n,), "<u8", wide, 8, (1,)).astype(np.uint64), np.ndarray((n,), ">u8", wide, 0, (1,)).astype(np.uint64)
    both, out, found = np.concatenate([after, before]), [none], [np.zeros((2, 0), np.int64)]
    shift = p.step + n * p.before
    for size, (first, bits) in p.keys.items():
        keys = after[: max(0, len(raw) - size + 1)] & np.uint64((1 << 8 * size) - 1)
        spot = _bucket(keys, bits)
        full = np.flatnonzero((np.diff(first) > 0)[spot])  # places whose bucket holds a piece
        start = first[spot[full]]
        count = first[spot[full] + 1] - start
        for lo in range(0, len(full), PLACES):
            many = count[lo : lo + PLACES]
            place = np.repeat(full[lo : lo + PLACES], many)
            piece = np.arange(len(place)) + np.repeat(start[lo : lo + PLACES] - np.cumsum(many) + many, many)
            near = both[place + shift[piece]]
            live = np.flatnonzero(near_mates(near, p.mate[piece], p.mask[piece]))
            live = live[keys[place[live]] == p.key[piece[live]]]
            found.append(np.stack([place[live], piece[live]]))
    place, piece = np.concatenate(found, axis=1)
    for lo in range(0, len(place), PLACES):
        at, of = place[lo : lo + PLACES], piece[lo : lo + PLACES]
        row = np.searchsorted(offsets, at, side="right") - 1
        begin, group = at - p.at[of], p.group[of]
        head = begin + p.group_at[group]
        a, b = np.maximum(head - p.group_edits[group], offsets[row]), np.minimum(head + p.group_bytes[group] + p.group_edits[group], offsets[row + 1])
        out.append(np.stack([row, p.item[of], begin], axis=1)[near_groups(p, group, raw, a, b)])
    return np.unique(np.concatenate(out), axis=0)


def build_index(ids: list[int | None], texts: list[str], tables: int, samples: int = SAMPLES, seed: int = 31, similarity: float = SIMILARITY) -> Index:
    items = [t.encode() for t in texts]
    raw = np.frombuffer(b"".join(items), np.uint8)
    offsets = np.cumsum([0, *map(len, items)])
    seeds, start, item = runs(raw, offsets)
    order = np.argsort(seeds, kind="stable")
    mask = np.zeros(1 << _MAP_BITS, bool)
    mask[(seeds >> np.uint64(64 - _MAP_BITS)).astype(np.int64)] = True
    rng = np.random.default_rng(seed)
    longest = max(map(len, items), default=0)
    walks = [rng.integers(0, 2, (2 * longest, 256), dtype=np.int64) * (np.arange(256) > 0) for _ in range(WALKS)]  # no place beyond is sampled
    each = -(-tables // WALKS)
    places = [(rng.random((each, 1, samples)) * (2 * np.diff(offsets))[None, :, None]).astype(np.int64) for _ in walks]
    sampled = [embed(raw, offsets[:-1], offsets[1:], w)[p, np.arange(len(items))[None, :, None]] for w, p in zip(walks, places, strict=True)]
    return Index(list(ids), items, seeds[order], item[order], (start - offsets[item])[order], mask, walks, places, sampled, cut(items, similarity))


def windows(index: Index, raw: np.ndarray, offsets: np.ndarray, similarity: float) -> np.ndarray:
    """Columns row, item, first byte and end of the distinct windows that a shared run lays."""
    h, start, doc = runs(raw, offsets)
    hot = np.flatnonzero(index.mask[(h >> np.uint64(64 - _MAP_BITS)).astype(np.int64)])
    lo, hi = np.searchsorted(index.seeds, h[hot]), np.searchsorted(index.seeds, h[hot], side="right")
    n = hi - lo
    at, seed = np.repeat(hot, n), np.repeat(lo, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    item, doc = index.seed_item[seed], doc[at]
    first = np.maximum(start[at] - index.seed_at[seed], offsets[doc])
    length = np.array([len(x) for x in index.items], np.int64)[item]
    end = np.minimum(first + length, offsets[doc + 1])
    keys = np.stack([doc, item, first, end], axis=1)[end - first >= length * similarity]
    return np.unique(keys, axis=0)


def matches(index: Index, raw: np.ndarray, offsets: np.ndarray, similarity: float) -> list[tuple[int, int, int, int]]:
    """(row, item, first byte, edits) of the best confirmed window of each row and item, over rows of normalised bytes."""
    parts = [windows(index, raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], similarity) + np.array([lo, 0, offsets[lo], offsets[lo]]) for lo, hi in chunks(offsets)]
    doc, item, first, end = np.concatenate([np.zeros((0, 4), np.int64), *parts]).T
    found = np.zeros(len(doc), bool)
    for lo in range(0, len(doc), WINDOWS):
        live = np.arange(lo, min(lo + WINDOWS, len(doc)))
        agreed, alike, seen = np.zeros(len(live), np.int64), np.zeros(len(live), bool), 0
        for n, (walk, places, sampled) in enumerate(zip(index.walks, index.places, index.sampled, strict=True), 1):
            emitted, own, rows = embed(raw, first[live], end[live], walk), item[live], np.arange(len(live))[:, None]
            for p, s in zip(places, sampled, strict=True):
                same = emitted[p[own], rows] == s[own]
                alike |= same.all(1)
                agreed, seen = agreed + same.sum(1), seen + same.shape[1]
            keep = agreed >= LEAST_AGREE * math.sqrt(n / len(index.walks)) * seen  # fewer places say less
            live, agreed, alike = live[keep], agreed[keep], alike[keep]
            if not len(live):
                break
        found[live] = alike
    out: dict[tuple[int, int], tuple[int, int]] = {}
    grams: dict[int, np.ndarray] = {}
    near_to: tuple[int, int, int] = (-1, -1, 0)
    for d, i, f in zip(doc[found].tolist(), item[found].tolist(), first[found].tolist(), strict=True):
        best, own = out.get((d, i)), index.items[i]
        if best is not None and best[0] == 0:
            continue
        limit = limit_of(own, similarity)
        if near_to[:2] == (d, i) and f <= near_to[2] + limit:
            continue  # piece_hits finds what the part read for near_to does not hold
        near_to = (d, i, f)
        near = raw[max(int(offsets[d]), f - limit) : min(int(offsets[d + 1]), f + len(own) + limit)]
        if i not in grams:
            grams[i] = trigrams(np.frombuffer(own, np.uint8))
        if np.minimum(grams[i], trigrams(near)).sum() < len(own) - 2 - 3 * limit:
            continue
        e = edits(own, near.tobytes(), limit)
        if e <= limit and (best is None or (e, f) < best):
            out[(d, i)] = (e, f)
    for lo, hi in chunks(offsets):
        hits = piece_hits(index.pieces, raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
        near_to = (-1, -1, 0)
        for d, i, f in (hits + np.array([lo, 0, offsets[lo]])).tolist():
            best, own = out.get((d, i)), index.items[i]
            limit = limit_of(own, similarity)
            if best is not None and best[0] == 0:
                continue
            if near_to[:2] == (d, i) and f <= near_to[2] + limit:
                continue  # the part read for near_to holds this one's
            near_to = (d, i, f)
            at = max(int(offsets[d]), f - limit)
            part = raw[at : min(int(offsets[d + 1]), f + len(own) + 2 * limit)]
            if i not in grams:
                grams[i] = trigrams(np.frombuffer(own, np.uint8))
            if np.minimum(grams[i], trigrams(part)).sum() < len(own) - 2 - 3 * limit:
                continue
            part = part.tobytes()
            e, end = _best(own, part)
            if e <= limit and (best is None or e < best[0]):
                _, back = _best(own[::-1], part[:end][::-1])
                out[(d, i)] = (e, at + end - back)
    return [(d, i, f - int(offsets[d]), e) for (d, i), (e, f) in out.items()]


def _search(index: Index, similarity: float):
    def run(batches):
        for batch in row_slices(batches, 2000):
            texts = pa.array([normalise(t.as_py()) for t in batch.column(1)], pa.large_string())
            raw, offsets = utf8(texts)
            rows = matches(index, raw, offsets, similarity)
            if rows:
                d, i, f, e = (np.array(c, np.int64) for c in zip(*rows, strict=True))
                ids = [index.ids[k] for k in i.tolist()]
                sim = 1 - e / np.array([len(index.items[k]) for k in i])
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(d)), pa.array(ids, pa.int64()), pa.array(f), pa.array(e), pa.array(sim)], ["doc_id", "item_id", "start_byte", "edits", "similarity"])

    return run


def find_leaks(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, recall: float = RECALL, block_bytes: int = BLOCK_BYTES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, item_id, start_byte (in the normalised text), edits, similarity: one row a document and item, the best window."""
    tables = tables_for(recall)
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
    kind = "doc_id long, item_id long, start_byte long, edits long, similarity double"
    out, ids, texts, size = None, [], [], 0

    def flush(out):
        found = rows.mapInArrow(_search(build_index(ids, texts, tables, similarity=similarity), similarity), kind)
        return found if out is None else out.unionByName(found)

    for r in benchmark.select("item_id", "text").where("text IS NOT NULL").orderBy("item_id", "text").toLocalIterator():
        text = normalise(r["text"])
        if not text:
            continue
        if ids and size + len(text) > block_bytes:
            out = flush(out)
            ids, texts, size = [], [], 0
        ids.append(r["item_id"])
        texts.append(text)
        size += len(text)
    if ids:
        out = flush(out)
    if out is None:
        return docs.sparkSession.createDataFrame([], kind)
    best = F.min(F.struct("edits", "start_byte", "similarity")).alias("b")
    return out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "b.start_byte", "b.edits", "b.similarity")


def query(spark, sf_dir: str) -> DataFrame:
    return find_leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def drop_leaks(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The documents without any benchmark passage, with their columns; rows of one text go or stay together."""
    key = F.xxhash64(docs["text"].cast("string"))
    found = find_leaks(docs.select(key.alias("doc_id"), docs["text"]), benchmark, similarity).select(F.col("doc_id").alias("__leak")).distinct()
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("rec"), key.alias("__key"))
    return rows.join(found, F.col("__key") == F.col("__leak"), "left_anti").select("rec.*")
