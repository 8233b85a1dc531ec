"""Products of packed blocks by twos: what travels does not depend on where entries lie."""

import numpy as np
import pytest

from rowproduct import catalog, multiply
from rowproduct.functions import blocks
from rowproduct.functions.semiring import PLUS_PAIR
from rowproduct.matrix import SparseMatrix, same_product
from rowproduct.operators.product import symbolic
from rowproduct.plans import cost, lowering
from rowproduct.sources.builders import supplier_follow


@pytest.fixture
def twos(monkeypatch):
    """Nothing is small enough to broadcast or to be fetched by blocks."""
    monkeypatch.setattr(lowering, "BLOCK_WORK", 20_000)
    monkeypatch.setattr(lowering, "FETCHED", 0)
    monkeypatch.setattr(lowering, "PAIR_ENTRIES", 2000)
    monkeypatch.setattr(lowering, "checked_broadcast", lambda df, rows=None: None)


@pytest.mark.parametrize("laid", [7, 1 << 20])
@pytest.mark.parametrize("big", [1, 1 << 24, 1 << 26, 0.25])
def test_two_blocks(monkeypatch, laid, big):
    monkeypatch.setattr(blocks, "LAID_OUT", laid)
    r = np.random.default_rng(2)
    for size, entries in ((12, 200), (10**13, 300), (3, 9)):
        ends = r.integers(0, size, 40)
        i, k, inner, j = (ends[r.integers(0, 40, entries)] for _ in range(4))
        v, w = (r.integers(-4, 5, entries) * big for _ in range(2))
        want, counts = {}, {}
        for a, b, x in zip(i.tolist(), k.tolist(), v.tolist(), strict=True):
            for c, d, y in zip(inner.tolist(), j.tolist(), w.tolist(), strict=True):
                if b == c:
                    want[a, d], counts[a, d] = want.get((a, d), 0) + x * y, counts.get((a, d), 0) + 1
        x, y = (blocks.opened(blocks.squeezed(blocks.packed(m[1], m[0], m[2]))) for m in ((i, k, v), (inner, j, w)))
        for ones, expect in ((False, want), (True, counts)):
            got = [np.concatenate(z).tolist() for z in zip(*blocks.pair_products(x, y, ones), strict=True)]
            assert dict(zip(zip(got[0], got[1], strict=True), got[2], strict=True)) == expect and len(got[0]) == len(expect)
        rows = {a: [sum(n for (b, _), n in counts.items() if b == a), int((i == a).sum()), sum(b == a for b, _ in counts)] for a, _ in counts}
        assert {a: list(z) for a, *z in zip(*(z.tolist() for z in blocks.pair_counts(x, y)), strict=True)} == rows
    none = blocks.packed(*(np.empty(0, np.int64),) * 3)
    assert not list(blocks.pair_products(x, none)) and not list(blocks.pair_products(none, y)) and not len(blocks.pair_counts(x, none)[0])


@pytest.mark.parametrize("name", ["cost_supplier_follow", "cost_by_matrix", "mcl_expand", "mcl_inflate", "mcl_clusters", "power3", "common_neighbours", "baseline_blocks"])
def test_queries_by_twos(spark, sf, monkeypatch, request, name):
    want = catalog.QUERIES[name](spark, sf).collect()
    real, seen = lowering.met_by_twos, []
    request.getfixturevalue("twos")
    monkeypatch.setattr(lowering, "met_by_twos", lambda *a: seen.append(real(*a)) or seen[-1])
    cells = lambda rows: sorted(tuple(round(x, 5) if isinstance(x, float) else x for x in r) for r in rows)
    assert cells(catalog.QUERIES[name](spark, sf).collect()) == cells(want) and seen
    plan = seen[0]._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "lineitem" not in plan


def test_values_by_twos(spark, sf, twos):
    m = supplier_follow(spark, sf)
    for o in ({}, {"semiring": PLUS_PAIR}):
        assert same_product(multiply(m, m, lowering="pairs", **o).df, multiply(m, m, lowering="joinagg", **o).df)
    t = [(i, (i * k) % 50, i - 25) for i in range(50) for k in range(1, 40)] + [(None, 3, 5), (4, None, 5), (5, 6, None)]
    odd = SparseMatrix(spark.createDataFrame(t, "i bigint, j bigint, v bigint").groupBy("i", "j").agg({"v": "sum"}).toDF("i", "j", "v"), 50, 50)
    assert not lowering.by_twos(odd, odd, 1 << 40)  # nulls go through joins
    assert symbolic(m, m).count() == cost.row_costs(m, m).count()


def test_cost_matrices_leave_nothing(spark, sf):
    """Each is stored once and deleted before the next but one; follow_sym is made from part_follow's triples."""
    from pathlib import Path
    from urllib.parse import urlparse

    from rowproduct.catalog import studies
    from rowproduct.plans import cut

    written, plans = len(cut._WRITTEN), []
    for name, m in studies.real_matrices(spark, sf):
        plans.append(name)
        assert m.nnz() == studies.src.BUILDERS[name](spark, sf).nnz()
    left = [path for _, path in cut._WRITTEN[written:] if Path(urlparse(path).path).exists()]
    assert sorted(plans) == sorted(n for n, _ in studies.REAL) and not left


@pytest.mark.parametrize("most", [4, 64, 1 << 22])
def test_column_heads(spark, most):
    """Ties by id, columns over several tasks, nulls, NaN: the largest of each column stay."""
    import random

    from rowproduct.operators import graphs

    rng = random.Random(4)
    t = [(i, j, rng.randrange(6) / 8) for i in range(60) for j in range(7) if rng.random() < 0.8] + [(70, 1, float("nan")), (None, 2, 0.5), (71, 3, None)]
    rng.shuffle(t)
    d = spark.createDataFrame(t, "i bigint, j bigint, p double").repartition(4)
    got = [tuple(r) for r in graphs.column_heads(d, 3, most).collect()]
    assert not any(repr(r) not in map(repr, t) for r in got) and len(got) == len(set(map(repr, got)))
    for j in range(7):
        want = sorted((r for r in t if r[1] == j and r[0] is not None and r[2] is not None and r[2] == r[2]), key=lambda r: (-r[2], r[0]))[:3]
        assert set(want) <= set(got)
    m = SparseMatrix(spark.createDataFrame([r for r in t if None not in r and r[2] == r[2]], "i bigint, j bigint, v double").repartition(4), 80, 7)
    plan = graphs.inflate(m, 2.0, 3).df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 1 and "Join" not in plan  # M is made once


@pytest.mark.parametrize("size", [4, 16, 300])
def test_dense_blocks_by_twos(size):
    r = np.random.default_rng(6)
    a, b = (r.integers(-3, 4, (60, 60)) * (r.random((60, 60)) < 0.2) for _ in range(2))
    x, y = (blocks.opened(blocks.squeezed(blocks.packed(m.nonzero()[1], m.nonzero()[0], m[m.nonzero()]))) for m in (a, b))
    c = np.zeros((60, 60), int)
    for i, j, v in blocks.dense_products(x, y, size):
        assert not c[i, j].any()
        c[i, j] = v
    assert (c == a @ b).all()
