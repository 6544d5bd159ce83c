"""Removal of repeated passages by suffix arrays.

A byte goes when a 400-byte string that covers it also starts somewhere else. Beside these strings the operator follows
passages of 50 words (runs of bytes above 0x20) that are shorter than 400 bytes; they are reported, not removed.

Suffix arrays of a whole corpus don't fit a machine, so the corpus is cut where nothing is lost: every string holds the
least hash among its 64-byte grams (its anchor), equal strings hold it at the same place, and an anchor's fragment is the
union of the strings that have it, with the byte beside either end. Anchors that occur once end here. Fragments that are
equal stand for each other; different fragments of one anchor meet in a task and are searched by a suffix array built in
two stages: only suffixes smaller than their successors are sorted directly, all others are induced by scans of the
buckets; then the common prefixes of neighbours in the array are measured.

An anchor with very many different fragments is anchored anew: its strings are dealt by their distance from the anchor
into blocks, and the bytes that all strings of a block hold become the new anchor, which is wider. Blocks shrink from
level to level, so groups fall apart; at the last level a block is one string and the anchor is all of it. No string is
left out at any level, and every group with different fragments is searched by a suffix array.

Texts are known by their md5; copies of one text are cut once. Texts stay where they are read; what moves are anchors,
fragments and the texts that lose bytes.

Edge cases: a null text counts as empty; texts under 400 bytes lose nothing; equal texts of 400 bytes or more lose all;
repeated rows are equal texts; ids are carried only, null or not; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rgsketch.llm.common import _INV, FILTER_BITS, bit_filter, chunks, filter_spot, in_filter, materialize, mix64, powers, prefix_hash, span_hash, utf8, words

LENGTH = 400
WORDS = 50
GRAM = 64
#: Different fragments of one anchor that one task searches; those of anchors with more are anchored anew.
GROUP = 600
#: Starts of strings in a block, in bytes and in words, of each new anchoring. The last is one string.
BLOCKS = ((32, 8), (4, 2), (1, 1))
#: Bytes of fragments in one suffix array.
ARRAY_BYTES = 3 << 17
#: The most bits of the filter of fragments that are searched (32 MB).
MOST_BITS = 1 << 28
#: Fragments that a task remembers as sent.
SENT = 500_000
#: Low bits of a gram's rank that hold its place, so that equal ranks go by place whatever was read beside them.
PLACE_BITS = 31
_U = np.uint64
_BLANK = np.arange(256) <= 0x20
_ODD = (_U(0x9E3779B97F4A7C15), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9))


class Corpus:
    """Bytes of some rows, their words and gram hashes, and all strings with their anchors' places."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, length: int, gram: int, n_words: int):
        self.raw, self.offsets, self.length, self.n_words = raw, offsets, length, n_words
        self.prefix = prefix_hash(raw)
        n = max(0, len(raw) - gram + 1)
        self.grams = (self.prefix[gram:] - self.prefix[:n]) * powers(_INV, n)
        size = np.diff(offsets)
        many = np.maximum(size - length + 1, 0)
        a = np.repeat(offsets[:-1], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        self.word, self.word_end, row = words(raw, offsets, _BLANK)
        first = np.arange(max(0, len(self.word) - n_words + 1))
        first = first[np.searchsorted(row, first, side="right") == np.searchsorted(row, first + n_words - 1, side="right")]
        span = self.word_end[first + n_words - 1] - self.word[first]
        self.first = first[(span < length) & (span >= gram)]
        self.start = np.concatenate([a, self.word[self.first]])
        self.end = np.concatenate([a + length, self.word_end[self.first + n_words - 1]])
        self.n_long = len(a)
        self.spot = self._least(gram)

    def _least(self, gram: int) -> np.ndarray:
        """Place of the least gram of each string, by minima of runs of a power of two from both ends."""
        out = np.zeros(len(self.start), np.int64)
        if not len(out):
            return out
        low = _U((1 << PLACE_BITS) - 1)
        run = (self.grams & ~low) | np.arange(len(self.grams), dtype=_U)
        width = self.end - self.start - gram + 1
        level = np.frexp(width)[1] - 1
        for k in range(int(level.max()) + 1):
            if k:
                half = 1 << (k - 1)
                run = np.minimum(run[:-half], run[half:])
            own = np.flatnonzero(level == k)
            if len(own):
                s = self.start[own]
                out[own] = (np.minimum(run[s], run[s + width[own] - (1 << k)]) & low).astype(np.int64)
        return out

    def _groups(self, pick: np.ndarray, block: tuple[int, int] | None):
        """Strings of pick in groups: (order of pick, first of each group, key of each group)."""
        spot = self.spot[pick]
        if block is None:
            order = np.argsort(spot, kind="stable")
            head = np.flatnonzero(np.concatenate(([True], np.diff(spot[order]) != 0)))
            return order, head, mix64(self.grams[spot[order[head]]])
        short = pick >= self.n_long
        at = np.searchsorted(self.word, spot, side="right") - 1  # the word that holds the anchor's first byte, or stands before it
        index = np.zeros(len(pick), np.int64)
        index[short] = self.first[pick[short] - self.n_long]
        wide = np.where(short, block[1], block[0])
        number = np.where(short, at - index, spot - self.start[pick]) // wide
        order = np.lexsort((number, spot, short))
        parts = [short[order], spot[order], number[order]]
        head = np.flatnonzero(np.concatenate(([True], np.any([x[1:] != x[:-1] for x in parts], axis=0))))
        g = order[head]
        lo, hi = spot[g] - number[g] * wide[g], spot[g] - (number[g] + 1) * wide[g] + 1 + self.length
        s = short[g]
        lo[s] = self.word[(at - number * wide)[g[s]]]
        hi[s] = self.word_end[(at - (number + 1) * wide)[g[s]] + self.n_words]
        key = mix64(span_hash(self.prefix, lo, hi) + number[g].astype(_U) * _ODD[1] + s.astype(_U) * _ODD[2])
        return order, head, key

    def fragments(self, hot: list[np.ndarray]) -> dict[str, np.ndarray]:
        """The fragments at level len(hot): row, place, key, frag, first byte and end of each, whether it begins and ends its
        row, and first byte and end of what its long and its short strings cover (equal if none). hot has the bit filters of
        the keys that were anchored anew, level by level."""
        pick = np.arange(len(self.start))
        for depth in range(len(hot) + 1):
            if not len(pick):
                break
            order, head, key = self._groups(pick, BLOCKS[depth - 1] if depth else None)
            if depth < len(hot):
                on = in_filter(hot[depth], (key & _U(FILTER_BITS - 1)).astype(np.int64))
                pick = np.sort(pick[order[np.repeat(on, np.diff(np.append(head, len(order))))]])
        if not len(pick):
            zero = np.zeros(0, np.int64)
            return {k: zero.astype(_U) if k in ("key", "frag") else zero for k in ("row", "pos", "key", "frag", "lo", "hi", "edge", "a0", "a1", "b0", "b1")}
        own = pick[order]
        short, s, e = own >= self.n_long, self.start[own], self.end[own]
        far = len(self.raw) + 1
        least = lambda x, on: np.minimum.reduceat(np.where(on, x, far), head)
        most = lambda x, on: np.maximum.reduceat(np.where(on, x, -1), head)
        a0, a1, b0, b1 = least(s, ~short), most(e, ~short), least(s, short), most(e, short)
        spot = self.spot[own[head]]
        row = np.searchsorted(self.offsets, spot, side="right") - 1
        lo, hi, edge = np.minimum(a0, b0), np.maximum(a1, b1), np.zeros(len(head), np.int64)
        if not (len(hot) and BLOCKS[len(hot) - 1] == (1, 1)):
            begins, ends = lo == self.offsets[row], hi == self.offsets[row + 1]
            edge = begins + 2 * ends
            lo, hi = lo - ~begins, hi + ~ends
        frag = mix64(span_hash(self.prefix, lo, hi) + (spot - lo).astype(_U) * _ODD[0] + edge.astype(_U) * _ODD[1])
        a0, a1, b0, b1 = (np.where(on, x - lo, 0) for x, on in ((a0, a1 >= 0), (a1, a1 >= 0), (b0, b1 >= 0), (b1, b1 >= 0)))
        return {"row": row, "pos": spot - self.offsets[row], "key": key, "frag": frag, "lo": lo, "hi": hi, "edge": edge, "a0": a0, "a1": a1, "b0": b0, "b1": b1}


def _read(column: pa.Array, length: int, gram: int, n_words: int):
    """(first row, Corpus) of each chunk of a batch's texts."""
    raw, offsets = utf8(column)
    for lo, hi in chunks(offsets):
        yield lo, Corpus(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], length, gram, n_words)


def _find_anchors(shape: tuple[int, int, int], hot: list[np.ndarray], rows: np.ndarray | None):
    names = ["txt", "pos", "key", "frag", "left", "a0", "a1", "b0", "b1"]

    def run(batches):
        for batch in batches:
            if rows is not None:
                batch = batch.take(pa.array(np.flatnonzero(in_filter(rows, batch.column(2).to_numpy()))))
            for at, corpus in _read(batch.column(1), *shape):
                f = corpus.fragments(hot)
                if len(f["row"]):
                    left = f["pos"] - (f["lo"] - corpus.offsets[f["row"]])
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).take(pa.array(f["row"] + at)), pa.array(f["pos"]), pa.array(f["key"].astype(np.int64)), pa.array(f["frag"].astype(np.int64)), pa.array(left.astype(np.int16)), *(pa.array(f[k].astype(np.int16)) for k in names[5:])], names)

    return run


def _split_ties(rank: np.ndarray, live: np.ndarray, key: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Split live's groups of equal rank by key, in place; order sorts live by rank and key. A rank is the place of its
    group's first member. Returns the members of groups of two and more, in order, and the first of each group."""
    live, key = live[order], key[order]
    old = rank[live]
    fresh = np.concatenate(([True], old[1:] != old[:-1]))
    head = np.flatnonzero(fresh | np.concatenate(([True], key[1:] != key[:-1])))
    n = np.diff(np.append(head, len(live)))
    outer = np.maximum.accumulate(np.where(fresh[head], head, 0))
    rank[live] = old + np.repeat(head - outer, n)
    tied = n > 1
    return live[np.repeat(tied, n)], np.cumsum(n[tied]) - n[tied]


def _sort_direct(text: np.ndarray, direct: np.ndarray, depth: int) -> np.ndarray:
    """direct, the places of all suffixes that are smaller than their successors, in order, right to ``depth`` bytes.

    A suffix is a row of pieces, each from one place of direct to the next. Pieces are ranked eight bytes at a time, then
    rows of several ranks, each round as many as one number holds, until the rows that are alike span ``depth`` bytes.
    Of two pieces of which one begins the other, the longer is smaller: where the shorter ends, its suffix is smaller than its
    successor and the other's isn't. So a piece goes on with 255, which no piece holds but past a suffix of 255s, of which none
    is in direct; the last one ends with the text and goes on with zeros.
    """
    m = len(direct)
    size = np.append(direct[1:] + 1, len(text)) - direct
    eight = words_of_eight(text, 0)
    fill = np.array([(1 << 64) - 1 >> 8 * k for k in range(9)], _U)
    rank, live = np.zeros(m, np.int64), np.arange(m)
    for at in range(0, depth, 8):
        word = eight[np.minimum(direct[live] + at, len(text) - 1)]
        pad = fill[np.clip(size[live] - at, 0, 8)]
        word = np.where(live < m - 1, word | pad, word & ~pad)
        live, head = _split_ties(rank, live, word, np.lexsort((word, rank[live])) if at else np.argsort(word))
        if not len(live):
            break
        goes_on = np.repeat(np.maximum.reduceat(size[live], head) > at + 8, np.diff(np.append(head, len(live))))
        live = live[goes_on]
        if not len(live):
            break
    bits = m.bit_length()
    per, held = 64 // bits, 1
    n = np.bincount(rank, minlength=m)
    live = np.flatnonzero(n[rank] > 1)
    place = np.append(direct, len(text))
    while True:
        live = live[place[np.minimum(live + held, m)] - place[live] < depth]
        if not len(live):
            return direct[np.argsort(rank)]
        after = np.append(rank + 1, 0)
        key = after[live].astype(_U)
        for k in range(1, per):
            key = key << _U(bits) | after[np.minimum(live + k * held, m)].astype(_U)
        live, _ = _split_ties(rank, live, key, np.argsort(key))
        held *= per


def two_stage_suffix_array(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffix array of uint8 text, right to ``depth`` bytes (ties beyond in any order).

    Suffixes smaller than their successors are sorted directly; the others are induced bucket by bucket: what precedes an
    entry of the scan and isn't smaller than it is appended to its first byte's bucket, in the order of the scan.
    """
    n = len(text)
    if n == 0:
        return np.zeros(0, np.int64)
    differs = text[1:] != text[:-1]
    change = np.flatnonzero(differs)
    nxt = np.concatenate(([0], np.cumsum(differs)))  # where the run of equal bytes ends decides the type
    small = np.zeros(n, bool)
    has = nxt < len(change)
    small[has] = (text[change] < text[change + 1])[nxt[has]]
    direct = np.flatnonzero(small)
    direct = _sort_direct(text, direct, depth) if len(direct) else direct
    heads = np.concatenate(([0], np.cumsum(np.bincount(text[direct], minlength=256))))
    queue: list[list[np.ndarray]] = [[] for _ in range(256)]
    queue[text[n - 1]].append(np.array([n - 1]))

    def deal(entries: np.ndarray, least: int) -> None:
        before = entries[entries > 0] - 1
        symbol = text[before]
        on = symbol >= least
        before, symbol = before[on], symbol[on]
        before = before[np.argsort(symbol, kind="stable")]
        size = np.bincount(symbol, minlength=256)
        edges = np.cumsum(size)
        for c in np.flatnonzero(size).tolist():
            queue[c].append(before[edges[c] - size[c] : edges[c]])

    out = []
    for c in range(256):
        done = []
        while queue[c]:  # entries of the same byte are appended while the last ones are scanned
            now, queue[c] = np.concatenate(queue[c]), []
            done.append(now)
            deal(now, c)
        own = direct[heads[c] : heads[c + 1]]
        if len(own):
            deal(own, c + 1)
        out += [*done, own]
    return np.concatenate(out)


def words_of_eight(text: np.ndarray, beyond: int) -> np.ndarray:
    """The eight bytes from each place on as one number, first byte highest; zeros past the end."""
    wide = np.concatenate([text, np.zeros(beyond + 8, np.uint8)])
    n = len(text) + beyond
    out = np.zeros(n, _U)
    for k in range(8):
        out |= wide[k : k + n].astype(_U) << _U(56 - 8 * k)
    return out


def common_prefixes(eight: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """Bytes that each suffix of order shares with the one before it, to ``depth``; 0 for the first."""
    out = np.zeros(len(order), np.int64)
    live, here, before = np.arange(1, len(order)), order[1:], order[:-1]
    for at in range(0, depth, 8):
        x = eight[here] ^ eight[before]
        alike = x == 0
        off = np.flatnonzero(~alike)
        if len(off):
            x = x[off]
            top = x >> _U(32)
            high = top > 0
            bits = np.frexp(np.where(high, top, x & _U(0xFFFFFFFF)).astype(np.float64))[1] + 32 * high  # place of the first bit that differs
            out[live[off]] = at + (64 - bits) // 8
            live, here, before = live[alike], here[alike], before[alike]
            if not len(live):
                break
        here, before = here + 8, before + 8
    out[live] = depth
    return np.minimum(out, depth)


def short_strings(text: np.ndarray, first: np.ndarray, sizes: np.ndarray, edge: np.ndarray, length: int, n_words: int) -> np.ndarray:
    """Bytes of the string of n_words whole words that begins at each place of the joined fragments; 0 where none does."""
    out = np.zeros(len(text), np.int64)
    start, end, row = words(text, np.append(first, len(text)), _BLANK)
    i = np.arange(max(0, len(start) - n_words + 1))
    of = np.searchsorted(row, i, side="right") - 1
    j = i + n_words - 1
    ok = j < row[of + 1]
    i, j, of = i[ok], j[ok], of[ok]
    ok = ((start[i] > first[of]) | (edge[of] & 1 > 0)) & ((end[j] < first[of] + sizes[of]) | (edge[of] & 2 > 0)) & (end[j] - start[i] < length)
    out[start[i[ok]]] = (end[j] - start[i])[ok]
    return out


def merge(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of half-open intervals as maximal runs."""
    if not len(starts):
        return starts, ends
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], np.maximum.accumulate(ends[order])
    new = np.concatenate(([True], starts[1:] > ends[:-1]))
    return starts[new], ends[np.append(np.flatnonzero(new)[1:] - 1, len(ends) - 1)]


def repeated_strings(parts: list[bytes], edge: np.ndarray, origin: np.ndarray, multi: np.ndarray, shared: np.ndarray, length: int, n_words: int = WORDS):
    """Maximal runs of long strings that also start at another origin, and of strings of both kinds that also stand in another
    text, as fragment, first byte in it and end. origin has text (high bits) and place of each fragment's first byte, multi
    and shared say that the fragment itself stands at several places, in several texts; edge that it begins (1) or ends (2)
    its text."""
    sizes = np.array([len(p) for p in parts])
    text = np.frombuffer(b"\0".join(parts) + b"\0", np.uint8)
    first = np.cumsum(sizes + 1) - sizes - 1
    each = lambda x: np.repeat(x, sizes + 1)
    room, base, flag = each(first + sizes) - np.arange(len(text)), each(origin - first), each(multi + 2 * shared.astype(np.int8))
    order = two_stage_suffix_array(text, length)
    eight = words_of_eight(text, length)
    long, across = [], []
    for size in (length, short_strings(text, first, sizes, edge, length, n_words)):
        fits = (size <= room) & (np.asarray(size) > 0)
        own = order[fits[order]]
        if not len(own):
            continue
        n = np.broadcast_to(size, len(text))[own]
        same = (common_prefixes(eight, own, length) >= n) & (n == np.roll(n, 1))
        same[0] = False
        head = np.flatnonzero(~same)
        place = base[own] + own
        doc = place >> 40
        flags = np.bitwise_or.reduceat(flag[own], head)
        differ = lambda x, bit, head=head, flags=flags: (np.minimum.reduceat(x, head) != np.maximum.reduceat(x, head)) | (flags & bit > 0)
        spread = lambda on, own=own, k=np.diff(np.append(head, len(own))): own[np.repeat(on, k)]
        if size is length:
            long.append(np.sort(spread(differ(place, 1))))
        start = np.sort(spread(differ(doc, 2)))
        across.append((start, start + np.broadcast_to(size, len(text))[start]))
    none = np.zeros(0, np.int64)
    hit = long[0] if long else none
    runs = [merge(hit, hit + length), merge(*(np.concatenate(x) for x in zip(*across, strict=True))) if across else (none, none)]
    out = []
    for start, end in runs:  # a zero byte lies between fragments, so no run goes over two
        of = np.searchsorted(first, start, side="right") - 1
        out.append((of, start - first[of], end - first[of]))
    return out


#: What a span says: its bytes go, its bytes stand in another text, or both.
GONE, SHARED, BOTH = 0, 1, 2
MARK = "key long, frag long, what int, starts array<int>, ends array<int>"


def _search_groups(length: int, n_words: int):
    """Over rows sorted by (key, frag), the mark row (multi set, part null) of a fragment first: it and the first copy of the
    bytes meet; bytes without a mark go at once, so an anchor that is not searched here holds no memory, however many
    fragments of it the filter lets pass. Groups of fragments are gathered up to ARRAY_BYTES and searched."""

    def flush(items):
        names: dict[bytes, int] = {}
        col = [np.array(x) for x in zip(*((names.setdefault(t, len(names)), at, edge, m, x) for _, _, _, t, at, edge, m, x in items), strict=True)]
        gone, both = repeated_strings([x[2] for x in items], col[2], (col[0].astype(np.int64) << 40) + col[1], col[3].astype(bool), col[4].astype(bool), length, n_words)
        n = len(items)
        many, many_x = np.bincount(gone[0], minlength=n), np.bincount(both[0], minlength=n)
        alike = (many > 0) & (many == many_x)
        g, x = alike[gone[0]], alike[both[0]]
        alike[gone[0][g][(gone[1][g] != both[1][x]) | (gone[2][g] != both[2][x])]] = False
        key, frag = (np.array([i[k] for i in items], np.int64) for k in (0, 1))
        for what, (of, start, end), on in ((BOTH, gone, alike), (GONE, gone, ~alike & (many > 0)), (SHARED, both, ~alike & (many_x > 0))):
            if on.any():
                mine = on[of]
                cut = pa.array(np.append(0, np.cumsum(np.bincount(of[mine], minlength=n)[on])), pa.int32())
                lists = [pa.ListArray.from_arrays(cut, pa.array(v[mine], pa.int32())) for v in (start, end)]
                yield pa.RecordBatch.from_arrays([pa.array(key[on]), pa.array(frag[on]), pa.array(np.full(on.sum(), what, np.int32)), *lists], ["key", "frag", "what", "starts", "ends"])

    def run(batches):
        items, size, now, mark = [], 0, None, (None,) * 4
        for batch in batches:
            for key, frag, part, txt, at, edge, multi, shared in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if key != now:
                    now = key
                    if size > ARRAY_BYTES:
                        yield from flush(items)
                        items, size = [], 0
                if part is None:
                    mark = key, frag, multi, shared
                elif mark[:2] == (key, frag):
                    items.append((key, frag, part, txt, at, edge, *mark[2:]))
                    size += len(part)
                    mark = (None,) * 4
        if items:
            yield from flush(items)

    return run


def _cut_fragments(table: np.ndarray, rows: np.ndarray, shape: tuple[int, int, int], hot: list[np.ndarray]):
    """Bytes of the fragments that the filters let pass, once a task (the memory of what was sent is bounded)."""

    def run(batches):
        sent: set[int] = set()
        for batch in batches:
            go = np.flatnonzero(in_filter(rows, batch.column(2).to_numpy()))
            if not len(go):
                continue
            batch = batch.take(pa.array(go))
            for base, corpus in _read(batch.column(1), *shape):
                f = corpus.fragments(hot)
                both = f["key"] ^ (f["frag"] * _ODD[0])
                keep = np.flatnonzero(in_filter(table, (both & _U(64 * len(table) - 1)).astype(np.int64)))
                if len(sent) > SENT:
                    sent.clear()
                new = []
                for i, x in zip(keep.tolist(), both[keep].tolist(), strict=True):
                    if x not in sent:
                        sent.add(x)
                        new.append(i)
                if new:
                    k = np.array(new)
                    data = corpus.raw.tobytes()
                    lo, row = f["lo"][k], f["row"][k]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(f["key"][k].astype(np.int64)), pa.array(f["frag"][k].astype(np.int64)), pa.array([data[x:y] for x, y in zip(lo.tolist(), f["hi"][k].tolist(), strict=True)], pa.binary()), batch.column(0).take(pa.array(row + base)), pa.array(lo - corpus.offsets[row]), pa.array(f["edge"][k].astype(np.int32))],
                        ["key", "frag", "part", "txt", "at", "edge"])

    return run


def _filter_bits(wanted: int) -> int:
    """Bits of a filter of so many values: eight each at least, up to MOST_BITS. Every row that it lets pass in vain is
    exchanged with its fragment's bytes, and in a filter of one size for all inputs these rows grow with their square."""
    return min(max(FILTER_BITS, 1 << max(0, 8 * wanted - 1).bit_length()), MOST_BITS)


def _bits(df: DataFrame, value: F.Column, bits: int = FILTER_BITS) -> np.ndarray:
    """A bit filter over the low bits of a 64-bit value."""
    spot = value.bitwiseAND(F.lit(bits - 1))
    rows = df.select(spot.alias("s")).select(F.shiftright("s", 6).cast("int").alias("cell"), F.expr("shiftleft(1L, cast(s & 63 as int))").alias("bit")).groupBy("cell").agg(F.bit_or("bit").alias("bits")).toArrow()
    out = np.zeros(bits // 64, np.int64)
    out[rows.column("cell").to_numpy()] = rows.column("bits").to_numpy()
    return out


def _apply(batches):
    for batch in batches:
        out = []
        for text, what, starts, ends in zip(*(c.to_pylist() for c in batch.columns[1:]), strict=True):
            data = text.encode()
            what, starts, ends = (np.array(x, np.int64) for x in (what, starts, ends))
            (s, e), (s2, e2) = (merge(starts[what != other], ends[what != other]) for other in (SHARED, GONE))
            h, at = hashlib.sha256(), 0
            for a, b in zip(s.tolist(), e.tolist(), strict=True):
                h.update(data[at:a])
                at = b
            h.update(data[at:])
            out.append((int((e - s).sum()), len(s), h.hexdigest(), int((e2 - s2).sum())))
        n, k, sha, shared = zip(*out, strict=True) if out else ([], [], [], [])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(k, pa.int64()), pa.array(sha, pa.string()), pa.array(shared, pa.int64())], ["txt", "n_removed", "n_spans", "kept_sha256", "n_shared"])


def _level(texts: DataFrame, shape: tuple[int, int, int], group: int, hot: list[np.ndarray], rows: np.ndarray | None):
    """Spans (txt, what, start, end) that the fragments of one level give, and a table of the keys to anchor anew with a text
    filter of theirs (None at the last level)."""
    spotted = texts.select("txt", "text", filter_spot("txt").alias("spot"))
    kind = "txt binary, pos long, key long, frag long, left short, a0 short, a1 short, b0 short, b1 short"
    found = materialize(spotted.mapInArrow(_find_anchors(shape, hot, rows), kind))
    place = F.xxhash64("txt", "pos")
    # written first: a join of two plain tables lets a hot anchor's rows be split over tasks
    twice = materialize(found.groupBy("key").agg(F.min(place).alias("lo"), F.max(place).alias("hi")).where("lo <> hi").select("key"))
    live = materialize(found.join(twice, "key"))
    frags = live.groupBy("key", "frag").agg(F.min(place).alias("lo"), F.max(place).alias("hi"), F.min("txt").alias("txt"), F.max("txt").alias("last"), *[F.max(c).alias(c) for c in ("a0", "a1", "b0", "b1")])
    frags = materialize(frags.select("key", "frag", (F.col("lo") != F.col("hi")).alias("multi"), (F.col("txt") != F.col("last")).alias("shared"), "txt", "a0", "a1", "b0", "b1"))
    kinds = frags.groupBy("key").agg(F.count("*").alias("kinds")).where("kinds > 1")
    search = materialize(frags.join(kinds.where(F.col("kinds") <= group), "key").select("key", "frag", "multi", "shared", "txt"))
    # a fragment that stands at several places is repeated with all its strings
    one = lambda what, a, b: F.struct(F.lit(what).alias("what"), F.array(a.cast("int")).alias("starts"), F.array(b.cast("int")).alias("ends"))
    both_lo = F.when(F.col("a1") == 0, F.col("b0")).when(F.col("b1") == 0, F.col("a0")).otherwise(F.least("a0", "b0"))
    marks = F.array(F.when(F.col("a1") > 0, one(GONE, F.col("a0"), F.col("a1"))), F.when(F.col("shared"), one(SHARED, both_lo, F.greatest("a1", "b1"))))
    whole = frags.where("multi").select("key", "frag", F.explode(F.array_compact(marks)).alias("m")).select("key", "frag", "m.*")
    bits = _filter_bits(search.count())
    table = _bits(search.select(_mixed(bits).alias("v")), F.col("v"), bits)
    parts = spotted.mapInArrow(_cut_fragments(table, bit_filter(search.select("txt").distinct(), "txt"), shape, hot), "key long, frag long, part binary, txt binary, at long, edge int")
    none = F.lit(None)
    meet = parts.withColumn("multi", none.cast("boolean")).withColumn("shared", none.cast("boolean")).unionByName(search.drop("txt"), allowMissingColumns=True)
    n = max(int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    meet = meet.repartition(n, "key").sortWithinPartitions("key", "frag", F.col("multi").isNull()).select("key", "frag", "part", "txt", "at", "edge", "multi", "shared")
    by_array = meet.mapInArrow(_search_groups(shape[0], shape[2]), MARK)
    marks = materialize(by_array.unionByName(whole))
    spans = live.join(marks, ["key", "frag"]).select("txt", "what", F.explode(F.arrays_zip("starts", "ends")).alias("s"), (F.col("pos") - F.col("left")).alias("at"))
    spans = spans.select("txt", "what", (F.col("s.starts") + F.col("at")).alias("start"), (F.col("s.ends") + F.col("at")).alias("end"))
    if len(hot) == len(BLOCKS):
        return spans, None, None
    again = kinds.where(F.col("kinds") > group).select("key")
    if again.isEmpty():
        return spans, None, None
    again = materialize(again)
    return spans, _bits(again, F.col("key")), bit_filter(live.join(again, "key").select("txt").distinct(), "txt")


def repeated_spans(texts: DataFrame, length: int = LENGTH, gram: int = GRAM, group: int = GROUP, n_words: int = WORDS) -> DataFrame:
    """(txt, what, starts, ends): places of repeated strings in distinct texts. texts has txt (md5) and text."""
    if not 0 < gram <= length < 1 << 14:
        raise ValueError("gram must not exceed length, nor length 16383")
    hot: list[np.ndarray] = []
    rows, spans = None, None
    while True:
        more, keys, rows = _level(texts, (length, gram, n_words), group, hot, rows)
        spans = more if spans is None else spans.unionByName(more)
        if keys is None:
            break
        hot = [*hot, keys]
    lists = spans.groupBy("txt").agg(F.collect_set(F.struct("what", "start", "end")).alias("all"))
    return lists.select("txt", F.col("all.what").alias("what"), F.col("all.start").alias("starts"), F.col("all.end").alias("ends"))


def _mixed(bits: int) -> F.Column:
    """Low bits of key ^ frag * odd constant modulo 2**64, by halves, as whole-number overflow is an error in ANSI mode."""
    low = bits - 1
    return F.col("key").bitwiseAND(F.lit(low)).bitwiseXOR((F.col("frag").bitwiseAND(F.lit(low)) * F.lit(0x9E3779B97F4A7C15 & low)).bitwiseAND(F.lit(low)))


def remove_repeats(df: DataFrame, length: int = LENGTH, gram: int = GRAM, group: int = GROUP, n_words: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, n_shared for every row.

    n_shared counts the bytes covered by strings of ``length`` bytes, or of n_words words and less bytes, that also stand in
    another row; words are runs of bytes above 0x20. A string shorter than ``gram`` has no anchor and isn't looked for.
    """
    text = F.coalesce(df[text_col].cast("string"), F.lit(""))
    rows = df.select(df[id_col].alias("doc_id"), F.unhex(F.md5(text.cast("binary"))).alias("txt"), text.alias("text"))
    texts = rows.select("txt", "text")
    size = F.octet_length("text").cast("long")
    short = F.regexp_replace("text", r"^[\x00-\x20]+|[\x00-\x20]+$", "")
    inner = F.when((size < length) & (size >= gram) & (F.regexp_count("text", F.lit(r"[^\x00-\x20]+")) >= n_words), F.octet_length(short)).otherwise(0)
    narrow = materialize(rows.select("doc_id", "txt", size.alias("n_bytes"), F.sha2(F.col("text").cast("binary"), 256).alias("sha"), inner.cast("long").alias("inner")))
    copies = materialize(narrow.where((F.col("n_bytes") >= length) | (F.col("inner") > 0)).groupBy("txt").count().where("count > 1").select("txt", F.lit(True).alias("copied")))
    spans = materialize(repeated_spans(texts, length, gram, group, n_words).join(copies, "txt", "left_anti"))  # copies go whole
    table = bit_filter(spans, "txt")

    def passing(batches):
        for batch in batches:
            go = np.flatnonzero(in_filter(table, batch.column(2).to_numpy()))
            if len(go):
                yield batch.take(pa.array(go)).select([0, 1])

    cut = texts.select("txt", "text", filter_spot("txt").alias("spot")).mapInArrow(passing, "txt binary, text string")
    cut = cut.join(spans, "txt").select("txt", "text", "what", "starts", "ends").mapInArrow(_apply, "txt binary, n_removed long, n_spans long, kept_sha256 string, n_shared long")
    known = materialize(cut.dropDuplicates(["txt"])).join(copies, "txt", "full_outer")
    out = narrow.join(known, "txt", "left")
    copied = F.coalesce("copied", F.lit(False))
    gone = copied & (F.col("n_bytes") >= length)
    return out.select(
        "doc_id", "n_bytes", F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(gone, 1).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"), F.when(gone, hashlib.sha256().hexdigest()).otherwise(F.coalesce("kept_sha256", "sha")).alias("kept_sha256"),
        F.when(gone, F.col("n_bytes")).when(copied, F.col("inner")).otherwise(F.coalesce("n_shared", F.lit(0))).cast("long").alias("n_shared"))


def query(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"))
