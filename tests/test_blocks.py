"""The NumPy blocks against plain Python."""

import numpy as np
import pytest

from rowproduct.functions import blocks


def entries(rng, n):
    p = np.unique(rng.integers(0, 40, (n, 2)), axis=0)
    return rng.permutation(p).T.astype(np.int64)


@pytest.mark.parametrize("laid_out", [8, 1000, 1 << 20])
@pytest.mark.parametrize("marks", [0, 16])
def test_row_sizes(monkeypatch, laid_out, marks):
    monkeypatch.setattr(blocks, "LAID_OUT", laid_out)
    monkeypatch.setattr(blocks, "MARKS", marks)
    rng = np.random.default_rng(1)
    for n in (0, 1, 30, 300):
        (i, k), (inner, j) = entries(rng, n), entries(rng, 250)
        rows = {}
        for a, b in zip(inner, j, strict=True):
            rows.setdefault(a, set()).add(b)
        want = {}
        for a, b in zip(i, k, strict=True):
            if b in rows:
                want.setdefault(a, set()).update(rows[b])
        got = blocks.row_sizes(i, k, inner, j)
        assert dict(zip(*(x.tolist() for x in got), strict=True)) == {a: len(x) for a, x in want.items()}
    assert not len(blocks.row_sizes(i, k, inner[:0], j[:0])[0])


@pytest.mark.parametrize("size", [3, 8, 64])
def test_dense_rows(size):
    """Any block row against the plain product; a block of the product is open at a time, however many columns there are."""
    rng = np.random.default_rng(2)
    (i, k), (inner, j) = entries(rng, 300), entries(rng, 250)
    v, w = rng.integers(-9, 9, len(i)), rng.integers(-9, 9, len(j))
    a, b = np.zeros((40, 40), int), np.zeros((40, 40), int)
    a[i, k], b[inner, j] = v, w
    got = np.zeros((40, 40), int)
    for block in range(-(-40 // size)):
        own = i // size == block
        r, c, x = blocks.dense_rows(i[own], k[own], v[own], inner, j, w, size)
        assert x.all() and (r // size == block).all()
        got[r, c] = x
    assert (got == a @ b).all()
    assert not len(blocks.dense_rows(*(x[:0] for x in (i, k, v, inner, j, w)), size)[0])


def test_dense_blocks_leave_the_engine_no_rdd(spark, sf):
    from rowproduct import catalog

    assert "ExistingRDD" not in catalog.QUERIES["baseline_blocks"](spark, sf)._jdf.queryExecution().executedPlan().toString()
