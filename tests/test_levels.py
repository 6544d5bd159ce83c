"""The nine pairs: chosen once a family, and by rough similarities where blocks are dense, with the result of a full search."""

import io

import numpy as np
import pyarrow as pa
import pytest

from rgsketch.operators import blocks, experiments
from rgsketch.queries import applications

LEVELS = (0.0, 0.1, 0.3, 0.5, 0.52, 0.7, 0.9, 1.0)


def _block(w, first):
    row, comp = np.nonzero(w)
    order = np.argsort(comp, kind="stable")
    out = io.BytesIO()
    np.savez(out, ids=np.arange(first, first + len(w)), l1=w.sum(1), comp=comp[order], row=row[order].astype(np.int32), weight=w[row, comp][order], sketch=np.zeros((len(w), 0), np.int32))
    return out.getvalue()


def _made(kind, sizes, rng):
    w = rng.random((sum(sizes), 20)) * (rng.random((sum(sizes), 20)) < 0.6) + 1e-3 * np.eye(20)[rng.integers(0, 20, sum(sizes))]
    if kind == "equal":  # many equal similarities: whole weights, and copies
        w = np.ceil(3 * w)
        w[1::7] = w[0]
    if kind == "norms":  # so different that rough similarities say nothing
        w *= 10.0 ** rng.integers(-4, 4, len(w))[:, None]
    if kind == "apart":  # the blocks share nothing
        w = np.concatenate([w, np.zeros_like(w)], 1)
        w[sizes[0] :] = np.roll(w[sizes[0] :], 20, 1)
    at = np.cumsum([0, *sizes])
    return w, [_block(w[lo:hi], lo) for lo, hi in zip(at[:-1], at[1:], strict=True)]


@pytest.mark.parametrize("kind", ["plain", "equal", "norms", "apart"])
def test_levels_equal_a_full_search(kind, monkeypatch):
    w, made = _made(kind, (130, 200, 7), np.random.default_rng(4))
    exact = []
    if kind in ("plain", "equal"):
        monkeypatch.setattr(blocks, "_minima", lambda a, b: exact.append(1))
    rows = [(i, k) for i in range(3) for k in range(i, 3)]
    batches = (pa.RecordBatch.from_arrays([pa.array([i]), pa.array([k]), pa.array([made[i]]), pa.array([made[k]])], ["k_a", "k_b", "d_a", "d_b"]) for i, k in rows)
    got = [r for b in blocks.meet_levels(LEVELS)(batches) for r in b.to_pylist()]
    lo = np.minimum(w[:, None], w[None]).sum(2)
    j = lo / (w.sum(1)[:, None] + w.sum(1) - lo)
    a, b = np.nonzero(np.triu(lo > 0, 1))
    assert not exact and len({(r["id_a"], r["id_b"]) for r in got}) == len(got) < len(a)
    for r in got:
        assert r["id_a"] < r["id_b"] and abs(r["j"] - j[r["id_a"], r["id_b"]]) < 1e-12
        assert abs(r["l1_a"] - w[r["id_a"]].sum()) + abs(r["l1_b"] - w[r["id_b"]].sum()) < 1e-9 * w.max()
    for x in LEVELS:
        want = min(zip(np.round(np.abs(j[a, b] - x), 9), a, b, strict=True))
        assert min((round(abs(r["j"] - x), 9), r["id_a"], r["id_b"]) for r in got) == want


def test_rough_similarities_stay_within_their_error():
    rng = np.random.default_rng(5)
    a, b = (rng.random((60, 90)) ** 4 * (rng.random((60, 90)) < 0.7) for _ in range(2))
    b[:, 0] = a[:, 3]
    turns, off = blocks._rough(a, b, a.sum(0), b.sum(0))
    lo = np.minimum(a[:, :, None], b[:, None]).sum(0)
    j = lo / (a.sum(0)[:, None] + b.sum(0) - lo)
    seen = 0
    for s, rough in turns:
        for r, row in enumerate(rough):
            seen += len(row)
            assert np.abs(row - j[np.arange(90), (np.arange(90) + s + r) % 90]).max() <= off < 0.02
    assert seen == 90 * 90


def test_families_choose_their_pairs_once(spark, monkeypatch):
    calls = []
    one = spark.createDataFrame([(1, 0.0, 0.0)], "k int, mae double, bias double")
    monkeypatch.setattr(experiments, "nine_pairs", lambda v: calls.append(1) or one)
    monkeypatch.setattr(experiments, "error_curve", lambda v, pairs, method, *a, **b: one)
    rows = applications._accuracy_families(spark, "/root/testdata/sf0.001").collect()
    assert len(calls) == len(applications.STUDIED) and len(rows) == 3 * len(calls)
