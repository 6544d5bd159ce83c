"""What op7's search of groups holds, and that its filter grows with what it is to let pass."""

import random
import tracemalloc

import pyarrow as pa

from rgsketch.llm import suffix_dedup

NAMES = ["key", "frag", "part", "txt", "at", "edge", "multi", "shared"]
TYPES = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int32(), pa.bool_(), pa.bool_()]


def _batch(rows):
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), TYPES, strict=True)], NAMES)


def test_unmarked_fragments_of_a_hot_anchor_hold_no_memory():
    """100,000 fragments of one anchor pass the filter without a mark; two marked fragments of another are still searched."""
    rng = random.Random(5)

    def batches():
        for k in range(100):
            yield _batch([(1, 1000 * k + i, rng.randbytes(700), b"t%d" % i, 0, 0, None, None) for i in range(1000)])
        common = bytes(range(65, 115))
        rows = []
        for frag, part in ((7, b"x" + common + b"y"), (8, b"z" + common + b"v")):
            rows += [(2, frag, None, None, None, None, False, False), *[(2, frag, part, b"d%d" % frag, 5, 0, None, None)] * 2]
        yield _batch(rows)

    tracemalloc.start()
    got = [r for b in suffix_dedup._search_groups(40, 50)(batches()) for r in b.to_pylist()]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert [(r["key"], r["frag"], r["what"], r["starts"], r["ends"]) for r in got] == [(2, f, suffix_dedup.BOTH, [1], [51]) for f in (7, 8)]
    assert peak < 40 << 20  # the fragments alone have 70 MB


def test_filter_grows_with_the_fragments_that_are_searched():
    for wanted in (0, 1, 2_000_000, 2_500_000, 9_500_000, 30_000_000):
        bits = suffix_dedup._filter_bits(wanted)
        assert bits & (bits - 1) == 0 and 8 * wanted <= bits <= max(suffix_dedup.FILTER_BITS, 32 * wanted)
    assert suffix_dedup._filter_bits(10**9) == suffix_dedup.MOST_BITS
