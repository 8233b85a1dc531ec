"""Forms that a size asks for: results stay whole where a broadcast or a fixed number of blocks would not do."""

import pathlib

import pytest

from rowproduct import catalog, multiply
from rowproduct.matrix import same_product
from rowproduct.operators import baselines
from rowproduct.plans import cost, lowering, work
from rowproduct.sources.builders import part_follow


@pytest.fixture
def few(monkeypatch):
    """No matrix is small enough to broadcast."""
    real = work.checked_broadcast
    for m in (lowering, __import__("rowproduct.catalog.matrices", fromlist=["x"])):
        monkeypatch.setattr(m, "checked_broadcast", lambda df, rows=None, most=10: real(df, rows, most))


def test_rowlocal_beyond_the_broadcast(spark, sf, few):
    m = part_follow(spark, sf)
    assert same_product(multiply(m, m, lowering="rowlocal").df, multiply(m, m, lowering="joinagg").df)


def test_join_broadcast_beyond_the_bound(spark, sf, few):
    m = part_follow(spark, sf)
    got = catalog.QUERIES["join_broadcast"](spark, sf)
    assert "ResolvedHint" not in got._jdf.queryExecution().analyzed().toString()
    assert same_product(got, multiply(m, m, lowering="joinagg").df)


@pytest.mark.parametrize("run", [lambda m: baselines.pooled(m, m, pool=64), lambda m: cost.probe_stats(m, m, accumulators=(("hash", 8),))])
def test_blocks_follow_the_work(spark, sf, monkeypatch, run):
    m, seen, real = part_follow(spark, sf), [], lowering.kernel
    monkeypatch.setattr(lowering, "KERNEL_WORK", 1000)
    monkeypatch.setattr(lowering, "kernel", lambda a, b, n, *r, **k: seen.append(n) or real(a, b, n, *r, **k))
    got = run(m)
    assert seen == [-(-work.total_work(m, m) // 1000)] and seen[0] > 8
    if "method" in got.columns:
        assert got.first()["ops"] == work.total_work(m, m)
    else:
        assert same_product(got, multiply(m, m, lowering="joinagg").df)


@pytest.mark.parametrize("name", ["clean_triples", "profile_example"])
def test_given_tables_are_read(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).inputFiles()


def test_row_sizes_by_block(spark, sf, monkeypatch):
    """Beyond a block's work sizes are counted where the products would lie: none is exchanged."""
    from rowproduct.operators.product import symbolic

    m = part_follow(spark, sf)
    want = {r.i: r.nnz for r in symbolic(m, m).collect()}
    costs = cost.costs(m, m).first()
    monkeypatch.setattr(lowering, "BLOCK_WORK", 1000)
    got = symbolic(m, m)
    assert "FlatMapCoGroupsInArrow" in got._jdf.queryExecution().optimizedPlan().toString()
    assert {r.i: r.nnz for r in got.collect()} == want
    assert cost.costs(m, m).first() == costs


@pytest.mark.parametrize("name", ["stream_session", "stream_tumbling"])
def test_streams_leave_nothing_on_the_driver(spark, sf, name):
    got = catalog.QUERIES[name](spark, sf)
    assert got.inputFiles() and not [t for t in spark.catalog.listTables() if t.name.startswith("stream_")]
    assert got.agg({"n": "sum"}).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()


@pytest.mark.parametrize("name", ["common_neighbours", "mcl_expand", "power3"])
def test_products_by_block_from_stored_triples(spark, sf, monkeypatch, name):
    """Where nothing is small enough to broadcast: no product is exchanged, and no factor is made again from its tables."""
    want = catalog.QUERIES[name](spark, sf).collect()
    monkeypatch.setattr(lowering, "checked_broadcast", lambda df, rows=None: None)
    got = catalog.QUERIES[name](spark, sf)
    assert "lineitem" not in got._jdf.queryExecution().executedPlan().toString()
    assert "REPARTITION_BY_NUM" in got._jdf.queryExecution().executedPlan().toString() and "bucket" in got._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want))


NO_TABLE = {"advise_synth": "events", "alloc_probe": "events", "heap_ablation": "events", "recipe_table": "lineitem", "scan_synth": "events", "schedule_probe": "events", "square_density": "events"}


@pytest.mark.parametrize("name", sorted(NO_TABLE))
def test_probes_and_generated_matrices_read_tables(spark, sf, tmp_path, name):
    """Without the table they must fail; with all of it they must account for its rows."""
    import os

    for f in os.listdir(sf):
        if f != f"{NO_TABLE[name]}.parquet":
            (tmp_path / f).symlink_to(f"{sf}/{f}")
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalog.QUERIES[name](spark, str(tmp_path)).collect()
    rows = spark.read.parquet(f"{sf}/events.parquet").count()
    if name == "scan_synth":
        assert catalog.QUERIES[name](spark, sf).agg({"v": "sum"}).first()[0] == rows
    if name == "alloc_probe":
        assert {r["mode"]: r["b"] for r in catalog.QUERIES[name](spark, sf).groupBy("mode").agg({"bytes": "sum"}).toDF("mode", "b").collect()} == {"single": 8 * rows, "parallel": 8 * rows}


def _pairs(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("name", ["doc_cosine", "embed_cosine"])
def test_pairs_of_rows_by_block(spark, sf, monkeypatch, name):
    """Where columns make as many products as there are pairs: blocks of rows meet by twos, and no product is exchanged."""
    from rowproduct.operators import graphs

    want = _pairs(catalog.QUERIES[name](spark, sf))
    monkeypatch.setattr(lowering, "BLOCK_WORK", 1000)
    monkeypatch.setattr(graphs, "PAIR_ROWS", 30)
    got = catalog.QUERIES[name](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Aggregate" not in plan and not {"documents", "embeddings"} & set(plan.replace("/", " ").replace(".", " ").split())
    assert _pairs(got) == want and (want or name == "embed_cosine")


@pytest.mark.parametrize("least", [-3, 0, 4])
@pytest.mark.parametrize("big", [1, 1 << 24, 1 << 28])
def test_pairs_of_rows_by_block_are_exact(spark, monkeypatch, least, big):
    """Negative values, repeated places, products that cancel, sums past what doubles and partial sums past what integers hold."""
    from rowproduct.matrix import SparseMatrix
    from rowproduct.operators import graphs

    t = [(i, k, ((i * 7 + k * 5) % 11 - 5) * big) for i in range(40) for k in range(9) if (i + k) % 3 or k == i % 9] + [(3, 1, big), (3, 1, -big), (50, 77, big)]
    m = SparseMatrix(spark.createDataFrame(t, "i bigint, j bigint, v bigint"), 100, 100)
    want = _pairs(graphs.cosine_pairs(m, least * big))
    monkeypatch.setattr(graphs, "PAIR_ROWS", 11)
    for width in (1, 1 / 128):  # columns laid out one by one, or nearly all in dense arrays
        monkeypatch.setattr("rowproduct.functions.blocks.DENSE", width)
        assert _pairs(graphs.block_pairs(m, least * big, 41, len(t))) == want


def _shuffles(spark):
    """Ids of the shuffles whose files lie on disk."""
    import re

    blocks = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllBlocks().mkString(" ")
    return set(re.findall(r"shuffle_(\d+)_", blocks))


def test_pairs_of_rows_leave_only_blocks_on_disk(spark, sf, monkeypatch):
    """Before pairs are made: the triples and the shuffles behind them are gone, and a block takes less room than its entries' values."""
    import time
    from urllib.parse import urlparse

    from rowproduct.operators import graphs
    from rowproduct.plans import cut
    from rowproduct.sources.builders import embed_rows

    monkeypatch.setattr(lowering, "BLOCK_WORK", 1000)
    monkeypatch.setattr(graphs, "PAIR_ROWS", 1000)
    written, shuffles, entries = len(cut._WRITTEN), _shuffles(spark), embed_rows(spark, sf).df.count()
    for name, most in (("embed_cosine", 8 * entries), ("doc_cosine", None)):
        pairs = catalog.QUERIES[name](spark, sf)
        triples, blocks = (urlparse(path).path for _, path in cut._WRITTEN[written:])
        size = sum(f.stat().st_size for f in pathlib.Path(blocks).rglob("*.parquet"))
        assert not pathlib.Path(triples).exists() and 0 < size and (most is None or size < most)
        for _ in range(40):  # files are deleted beside what goes on
            if len(left := _shuffles(spark) - shuffles) < 2:
                break
            time.sleep(0.1)
        assert len(left) < 2, left
        written = len(cut._WRITTEN)
        assert pairs.where("i >= j").count() == 0


def test_squeezed_blocks_open_as_they_were():
    import numpy as np
    import pyarrow as pa

    from rowproduct.functions.blocks import opened, packed, squeezed

    ends = [-(1 << 63), -(1 << 40), -129, -128, -1, 0, 127, 128, 255, 256, 65535, 65536, 1 << 32, (1 << 63) - 1]
    i, k = (x.ravel() for x in np.meshgrid(np.array(ends), np.array(ends)))
    for n in range(1, len(ends) + 1):
        for v in (np.resize(np.array(ends[:n]), len(i)), np.resize(np.array(ends[-n:]), len(i)), np.resize(np.array(ends) / 3, len(i))):
            for some in (slice(None), slice(0, 1), slice(3, 40, 2)):
                block = packed(i[some], k[some], v[some])
                got = opened(pa.py_buffer(squeezed(block)))
                assert all(np.array_equal(got[c], block[c]) for c in block) and (got["vals"].dtype.kind == "f") == (v.dtype.kind == "f")


@pytest.mark.parametrize("name", ["tri_count", "tri_count_copurchase"])
def test_triangles_by_block(spark, sf, monkeypatch, name):
    """Beyond a block's work paths are counted where they are made, and none is exchanged; the count stays."""
    from rowproduct.operators import graphs

    want = catalog.QUERIES[name](spark, sf).collect()
    real, plans = graphs.triangles_by_block, []
    monkeypatch.setattr(graphs, "triangles_by_block", lambda *a: plans.append(real(*a)) or plans[-1])
    monkeypatch.setattr(lowering, "BLOCK_WORK", 1000)
    assert catalog.QUERIES[name](spark, sf).collect() == want and want[0][0] > 0
    plan = plans[0]._jdf.queryExecution().optimizedPlan().toString()
    assert "CoGroupsInArrow" in plan and "lineitem" not in plan


def test_closed_paths_of_sparse_and_heavy_rows(monkeypatch):
    import numpy as np

    from rowproduct.functions import blocks

    r = np.random.default_rng(3)
    for size, edges in ((30, 300), (10_000, 3000)):
        i, j = np.unique(np.sort(r.integers(0, size, (edges, 2)) * 10**12, 1), axis=0).T
        i, j = i[i != j], j[i != j]
        have = set(zip(i.tolist(), j.tolist(), strict=True))
        want = sum((a, c) in have for a, b in have for k, c in have if k == b) if size == 30 else len({(a, b, c) for a, b in have for k, c in have if k == b and (a, c) in have})
        for laid in (7, 1 << 20):
            monkeypatch.setattr(blocks, "LAID_OUT", laid)
            assert blocks.closed_paths(i, j, i, j) == want


def test_rows_fetched_for_a_joined_factor(spark, sf, monkeypatch):
    """A factor that a join makes meets the rows that its blocks fetched; the query's factors are stored first."""
    from rowproduct.sources.builders import cust_part, part_supp

    a, b = cust_part(spark, sf), part_supp(spark, sf)
    want = multiply(a, b, lowering="joinagg").df
    got = multiply(a, b, lowering="rowfetch").df
    assert same_product(got, want)
    monkeypatch.setattr(lowering, "checked_broadcast", lambda df, rows=None: None)
    got = catalog.QUERIES["product_rectangular"](spark, sf)
    assert "lineitem" not in got._jdf.queryExecution().executedPlan().toString() and same_product(got, want)
