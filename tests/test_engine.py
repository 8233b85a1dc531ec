import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from rowproduct import SparseMatrix, multiply
from rowproduct.functions import kernels
from rowproduct.functions.semiring import MIN_PLUS, OR_AND, PLUS_PAIR
from rowproduct.matrix import clean, same_product, to_rows
from rowproduct.operators import algebra, graphs
from rowproduct.operators.product import Inspector, ProductOptions, symbolic, symbolic_approx
from rowproduct.plans import advisor, cost, lowering, schedule
from rowproduct.plans.work import prefix_sum, row_work, total_work
from rowproduct.sources import builders, synth


def matrix(spark, dense):
    dense = np.asarray(dense)
    i, j = np.nonzero(dense)
    rows = [(int(a), int(b), int(dense[a, b])) for a, b in zip(i, j)]
    return SparseMatrix(spark.createDataFrame(rows, "i bigint, j bigint, v bigint"), *dense.shape)


def dense(m):
    out = np.zeros((m.nrows, m.ncols), np.int64)
    for r in m.df.collect():
        out[r.i, r.j] += r.v
    return out


A = [[2, 0, 1, 0], [0, 0, 0, 0], [0, 3, 1, 4], [0, 0, 0, 5]]
B = [[0, 1, 0, 2], [4, 0, 0, 0], [0, 3, 1, -4], [0, 0, 0, 0]]


@pytest.fixture(scope="module")
def ab(spark):
    return matrix(spark, A), matrix(spark, B)


def test_hand_example(spark, ab):
    a, b = ab
    assert {r.i: r.work for r in row_work(a, b).collect()} == {0: 5, 1: 0, 2: 4, 3: 0} and total_work(a, b) == 9
    got = {(r.i, r.j): r.v for r in multiply(a, b).df.collect()}
    assert got == {(0, 1): 5, (0, 2): 1, (0, 3): -2 + 2, (2, 0): 12, (2, 1): 3, (2, 2): 1, (2, 3): -4}  # one place cancels and stays
    c = cost.costs(a, b).first()
    assert (c.work, c.nnz_c) == (9, 7) and abs(c.cr - 9 / 7) < 1e-12
    assert c.t_heap == 11.34 and c.t_hash_sorted == 21.755 and c.t_hash_unsorted == 9.0
    for blocks, want in ((2, [0, 1, 1, 1]), (3, [0, 1, 1, 2])):
        assert [r.bucket for r in schedule.balanced(row_work(a, b), blocks).orderBy("i").collect()] == want
    assert kernels.table_capacity(5, 4) == 8


OPTIONS = ([{"accumulator": x, "phases": p, "order": o} for x in ("hash", "chunk", "dense") for p in (1, 2) for o in ("sorted", "unsorted") if x == "hash" or (p, o) == (1, "unsorted")]
           + [{"accumulator": "heap"}, {"accumulator": "pooled", "phases": 1}, {"accumulator": "sortagg", "order": "sorted"}]
           + [{"lowering": x, "schedule": s} for x in ("joinagg", "rowlocal", "rowfetch", "splithub") for s in ("balanced", "static", "hashed") if x == "rowfetch" or s == "balanced"])


@pytest.mark.parametrize("o", OPTIONS, ids=str)
def test_every_method_gives_one_product(spark, o):
    rng = np.random.default_rng(5)
    x = rng.integers(-3, 4, (13, 9)) * (rng.random((13, 9)) < 0.4)
    y = rng.integers(-3, 4, (9, 21)) * (rng.random((9, 21)) < 0.4)
    y[:, 3] = 0
    a, b = matrix(spark, x), matrix(spark, y)
    c = multiply(a, b, blocks=5, **o)
    assert (c.nrows, c.ncols) == (13, 21) and (dense(c) == x @ y).all()
    want = (np.abs(x) > 0).astype(int) @ (np.abs(y) > 0).astype(int)
    places = {(r.i, r.j) for r in c.df.collect()}
    assert places == set(zip(*map(lambda t: t.tolist(), np.nonzero(want))))
    if c.row_order == "sorted":
        for part in c.df.rdd.glom().collect():
            seq = [(r.i, r.j) for r in part]
            assert seq == sorted(seq)


CASES = {"zero": np.zeros((4, 4), int), "identity": np.eye(5, dtype=int), "row": np.ones((1, 7), int), "column": np.ones((7, 1), int), "full": np.arange(1, 17).reshape(4, 4), "hub": np.vstack([np.ones((1, 6), int), np.eye(6, dtype=int)[1:]])}


@pytest.mark.parametrize("name", CASES)
def test_edge_shapes(spark, name):
    x = CASES[name]
    m = matrix(spark, x)
    for o in ({"lowering": "joinagg"}, {"lowering": "rowfetch"}, {"accumulator": "hash"}, {"accumulator": "heap"}):
        assert (dense(multiply(m, m.transpose(), blocks=50, **o)) == x @ x.T).all()


def test_splithub_shares_rows(spark):
    x = np.ones((3, 40), int)
    m = matrix(spark, x)
    from rowproduct.functions.semiring import PLUS_TIMES

    out = m.with_df(lowering.splithub(m, m.transpose(), PLUS_TIMES, target=10), ncols=3)
    assert (dense(out) == x @ x.T).all()


def test_bad_calls(spark, ab):
    a, b = ab
    with pytest.raises(ValueError):
        multiply(a, SparseMatrix(b.df, 5, 4))
    with pytest.raises(ValueError):
        ProductOptions(accumulator="heap", phases=2)
    with pytest.raises(ValueError):
        multiply(a, b, accumulator="hash", semiring=MIN_PLUS)


@settings(max_examples=60, deadline=None, suppress_health_check=[HealthCheck.too_slow])
@given(st.integers(0, 2**32 - 1), st.sampled_from(["hash", "chunk", "heap", "dense", "pooled"]), st.sampled_from([1, 2]), st.sampled_from([8, 16]))
def test_kernels_against_dense(seed, name, phases, lanes):
    rng = np.random.default_rng(seed)
    n, k, m = rng.integers(1, 12, 3)
    x = rng.integers(-4, 5, (n, k)) * (rng.random((n, k)) < 0.5)
    y = rng.integers(-4, 5, (k, m)) * (rng.random((k, m)) < 0.5)
    rows = [(i, [(j, int(x[i, j])) for j in np.nonzero(x[i])[0].tolist()]) for i in range(n)]
    b = {i: (np.nonzero(y[i])[0].tolist(), [int(v) for v in y[i][np.nonzero(y[i])[0]]]) for i in range(k) if y[i].any()}
    out, tally = kernels.multiply_block(rows, b, int(m), name, lanes, 1 if name == "heap" else phases, "sorted", pool=3)
    got = np.zeros((n, m), int)
    work = 0
    for i, row in out:
        assert name == "pooled" or [c for c, _ in row] == sorted(c for c, _ in row)
        for c, v in row:
            got[i, c] += v  # the pooled table gives a row in parts
    work = sum(len(b[j][0]) for i in range(n) for j in np.nonzero(x[i])[0].tolist() if j in b)
    assert (got == x @ y).all()
    assert name != "pooled" or tally.peak <= 3
    assert tally.ops == work * (2 if phases == 2 and name in ("hash", "chunk") else 1) and tally.probes >= tally.ops


def test_chunks_compare_as_a_whole():
    t = kernels.ChunkTable(16, 8)
    for c in (5, 9, 5, 1 << 40, 9):
        t.add(c, 1)
    assert dict(t.take()) == {5: 2, 9: 2, 1 << 40: 1} and t.take() == [] and (t.keys == t.EMPTY).all()
    assert kernels.bits(np.array([0, 1, 0, 1], bool)) == 10 and kernels.first_lane(10) == 1
    full = kernels.ChunkTable(8, 8)
    for c in range(8):
        full.add(c, c)
    assert full.find(3)[1] == 3 and full.tally.probes == 9


def test_pool_is_bounded():
    t = kernels.PooledTable(4)
    parts = [p for c in range(1000) for p in t.add(c % 7, 1)] + t.take()
    total = {}
    for c, v in parts:
        total[c] = total.get(c, 0) + v
    assert t.tally.peak == 4 and total == {c: len(range(c, 1000, 7)) for c in range(7)}


def test_advice_drives_the_product(spark, sf, monkeypatch):
    from rowproduct.operators import product
    from rowproduct.plans.advisor import advise, stats_of

    m = builders.supplier_follow(spark, sf)
    want = {(r.i, r.j): r.v for r in multiply(m, m).df.collect()}
    for order in ("sorted", "unsorted"):
        for op, source in (("AxA", "real"), ("AxA", "synthetic"), ("tall", "synthetic"), ("LxU", "real")):
            method = advise(stats_of(m, m), op, source, order).method
            asked = []
            own = product.low.kernel
            monkeypatch.setattr(product.low, "kernel", lambda *a, **k: asked.append(a[3]) or own(*a, **k))
            got = multiply(m, m, accumulator="advised", order=order, op=op, source=source)
            assert asked == ([] if method == "inspector" else [method]) and got.row_order == ("sorted" if order == "sorted" or method == "heap" else "unsorted")
            monkeypatch.setattr(product.low, "kernel", own)
    assert {(r.i, r.j): r.v for r in got.df.collect()} == want


def test_counts_through_split_hubs(spark, sf):
    from rowproduct.functions.semiring import PLUS_PAIR
    from rowproduct.plans import lowering

    m = builders.part_follow(spark, sf)
    want = {tuple(r) for r in lowering.joinagg(m, m, PLUS_PAIR).collect()}
    assert {tuple(r) for r in lowering.splithub(m, m, PLUS_PAIR, target=20).collect()} == want


def test_probes_fall_with_lanes(spark, sf):
    m = builders.part_follow(spark, sf)
    c = {r.method: r.collision for r in cost.probe_stats(m, m).collect()}
    assert 1 <= c["chunk16"] <= c["chunk8"] <= c["hash"] < 2


def test_balanced_blocks_hold_their_bound(spark, sf):
    m = builders.term_bigram(spark, sf)
    w = row_work(m, m, all_rows=False)
    total, most = w.agg({"work": "sum"}).first()[0], w.agg({"work": "max"}).first()[0]
    for p in (3, 16, 64):
        t = schedule.block_table(schedule.balanced(w, p)).orderBy("bucket").collect()
        assert all(r.work <= total / p + most for r in t) and sum(r.work for r in t) == total
        assert all(a.row_hi < b.row_lo for a, b in zip(t, t[1:]))


def test_prefix_sum(spark):
    rng = np.random.default_rng(1)
    v = rng.integers(0, 100, 1000)
    d = spark.createDataFrame([(int(i), int(x)) for i, x in enumerate(v)], "i bigint, work bigint").repartition(7)
    got = [r.before for r in prefix_sum(d, ["i"], "work", parts=9).orderBy("i").collect()]
    assert got == (np.cumsum(v) - v).tolist()


def test_generated_sizes(spark):
    """Known sizes at scale 10, and the method that the formulas pick."""
    want = {("uniform", 4): (4089, 16262, 16131, 35495, 84120, "heap"), ("uniform", 8): (8159, 64966, 62974, 200555, 445332, "heap"), ("uniform", 16): (16255, 258369, 229012, 1042084, 2054428, "heap"),
            ("skewed", 4): (3596, 97404, 60382, 335338, 537168, "heap"), ("skewed", 8): (6695, 289736, 138003, 1186757, 1404566, "heap"), ("skewed", 16): (12040, 804763, 268915, 3794639, 3145190, "hash")}
    for (kind, ef), (nnz, work, nc, heap, hash_, pick) in want.items():
        m = synth.synth(spark, 10, ef, kind)
        c = cost.costs(m, m).first()
        assert (m.nnz(), c.work, c.nnz_c) == (nnz, work, nc) and (round(c.t_heap), round(c.t_hash_sorted)) == (heap, hash_)
        s = advisor.ProductStats(nnz, nnz, work, nc, c.cr, ef, kind, 0, c.t_heap, c.t_hash_sorted, c.t_hash_unsorted)
        choice = advisor.advise(s, "AxA", "synthetic", "sorted", edge_factor=ef)
        assert choice.cost_choice == choice.recipe_choice == pick and choice.basis == "recipe"
    assert cost.skew_class(synth.synth(spark, 8, 16, "skewed")) == "skewed" and cost.skew_class(synth.synth(spark, 8, 16, "uniform")) == "uniform"


def test_advice_cells(spark):
    base = advisor.ProductStats(1, 1, 10, 5, 2.0, 8.0, "skewed", 1, 1.0, 2.0, 3.0)
    high = advisor.ProductStats(1, 1, 10, 4, 2.5, 9.0, "uniform", 1, 1.0, 2.0, 3.0)
    pick = lambda s, *a: advisor.advise(s, *a).method
    assert pick(base, "AxA", "real", "unsorted") == "hash" and pick(high, "AxA", "real", "unsorted") == "inspector"
    assert pick(base, "LxU", "real", "sorted") == "heap" and pick(high, "LxU", "real", "sorted") == "hash"
    assert pick(base, "tall", "synthetic", "sorted") == "hash"
    assert advisor.advise(high, "tall", "synthetic", "sorted").basis == "cost" and advisor.advise(base, "LxU", "real", "unsorted").basis == "cost"
    assert len(advisor.RECIPE) == 18


def test_workload_sizes(spark, sf):
    m = builders.part_follow(spark, sf)
    c = cost.costs(m, m).first()
    assert (m.nnz(), c.work, c.nnz_c) == (2736, 38216, 24214)
    assert multiply(m, m).df.agg({"v": "sum"}).first()[0] == 27051960
    s = builders.supplier_follow(spark, sf)
    c = cost.costs(s, s).first()
    assert (c.work, c.nnz_c) == (810, 100)


def test_triangles_three_ways(spark, sf):
    for build, want in ((builders.follow_sym, 3287), (builders.copurchase, 125968)):
        m = build(spark, sf)
        assert graphs.triangle_count(m).first()[0] == want
        assert graphs.triangles_by_vertex(m).agg({"tri": "sum"}).first()[0] == 3 * want
    low, up = graphs.split(graphs.reorder(builders.follow_sym(spark, sf)))
    z = multiply(low, up, semiring=PLUS_PAIR)
    assert total_work(low, up) == 40946 and z.nnz() == 18151
    assert graphs.wedges(builders.follow_sym(spark, sf)).nnz() == 18151


def test_symbolic_and_inspector(spark, sf):
    m = builders.part_follow(spark, sf)
    exact = {r.i: r.nnz for r in symbolic(m, m).collect()}
    assert exact == {r.i: r["count"] for r in multiply(m, m).df.groupBy("i").count().collect()}
    near = {r.i: r.nnz for r in symbolic_approx(m, m).collect()}
    assert np.mean([abs(near[i] - n) / n for i, n in exact.items()]) < 0.06
    ins = Inspector(m, m)
    twice = algebra.apply(m, lambda v: v * 2)
    assert same_product(ins.execute(twice, m).df, multiply(twice, m, lowering="joinagg").df)


def test_algebra_identities(spark):
    rng = np.random.default_rng(9)
    x, y, z = (matrix(spark, rng.integers(-2, 3, (8, 8))) for _ in range(3))
    assert same_product(algebra.prune_below(algebra.apply(multiply(x, y).transpose(), lambda v: v), -10**9).df, multiply(y.transpose(), x.transpose()).df)
    assert (dense(multiply(algebra.ewise_add(x, y), z)) == (dense(x) + dense(y)) @ dense(z)).all()
    assert (dense(algebra.chain(x, y, z)) == dense(x) @ dense(y) @ dense(z)).all()
    assert (dense(algebra.power(x, 5)) == np.linalg.matrix_power(dense(x), 5)).all()


def test_decimal_and_double_products(spark):
    d = spark.createDataFrame([(0, 0, "1.25"), (0, 1, "2.50"), (1, 1, "-3.00")], "i bigint, j bigint, s string")
    m = SparseMatrix(d.selectExpr("i", "j", "cast(s as decimal(12,2)) v"), 2, 2)
    got = {(r.i, r.j): float(r.v) for r in multiply(m, m).df.collect()}
    assert got == {(0, 0): 1.5625, (0, 1): -4.375, (1, 1): 9.0}
    f = SparseMatrix(d.selectExpr("i", "j", "cast(s as double) v"), 2, 2)
    for o in ({}, {"accumulator": "hash"}, {"accumulator": "dense"}):
        assert {(r.i, r.j): r.v for r in multiply(f, f, **o).df.collect()} == got
    with pytest.raises(TypeError):
        multiply(m, m, accumulator="hash")


def test_wide_ids(spark):
    big = 1 << 40
    m = SparseMatrix(spark.createDataFrame([(big, big + 1, 2), (big + 1, big, 3)], "i bigint, j bigint, v bigint"), 1 << 41, 1 << 41)
    for o in ({"lowering": "joinagg"}, {"lowering": "rowfetch", "schedule": "hashed"}, {"accumulator": "hash", "schedule": "hashed"}):
        assert {(r.i, r.j, r.v) for r in multiply(m, m, **o).df.collect()} == {(big, big, 6), (big + 1, big + 1, 6)}


def test_clean(spark):
    d = spark.createDataFrame([(0, 1, 2), (0, 1, -2), (None, 1, 4), (1, 1, 3)], "i bigint, j bigint, v bigint")
    assert {(r.i, r.j, r.v) for r in clean(d).collect()} == {(0, 1, 0), (1, 1, 3)} and clean(d, keep_zeros=False).count() == 1


def test_profile_example(spark):
    t = spark.createDataFrame([("a", "x", 1.0), ("a", "y", 3.0), ("b", "x", 4.0), ("b", "y", 2.0)], "problem string, method string, cost double")
    assert {(r.problem, r.method): r.score for r in cost.scores(t).collect()} == {("a", "x"): 1, ("a", "y"): 3, ("b", "x"): 2, ("b", "y"): 1}
    p = {(r.method, r.tau): r.share for r in cost.performance_profile(t, [1, 2, 3]).collect()}
    assert p == {("x", 1): 0.5, ("y", 1): 0.5, ("x", 2): 1, ("y", 2): 0.5, ("x", 3): 1, ("y", 3): 1}


def test_published_ratios():
    """Multiplications over entries of A: exactly four where every row has four; low ratios by count."""
    flop_nnz = {"m133-b3": (3.2, 3.18), "mac_econ": (7.56, 6.7), "mario002": (12.83, 6.45), "mc2depi": (8.39, 5.25), "patents_main": (2.6, 2.28), "scircuit": (8.68, 5.22), "webbase-1M": (69.52, 51.11), "delaunay_n24": (633.91, 347.32)}
    assert all(f / z <= advisor.CR_LIMIT for f, z in flop_nnz.values()) and 3.2 / 0.8 == 4.0


def test_searches(spark, sf):
    m = builders.part_follow(spark, sf)
    edges = {}
    for r in m.df.collect():
        edges.setdefault(r.i, set()).add(r.j)
    want = {}
    for k, s in enumerate((0, 5)):
        level, at = {s: 0}, [s]
        while at:
            at = sorted({j for i in at for j in edges.get(i, ()) if j not in level})
            level.update((j, max(level.values()) + 1) for j in at)
        want |= {(k, v): n for v, n in level.items()}
    # levels by rounds: recompute exactly
    want = {}
    for k, s in enumerate((0, 5)):
        seen, at, n = {s: 0}, {s}, 0
        while at:
            n += 1
            at = {j for i in at for j in edges.get(i, ()) if j not in seen}
            seen |= dict.fromkeys(at, n)
        want |= {(k, v): n for v, n in seen.items()}
    assert {(r.search, r.vertex): r.level for r in graphs.msbfs(m, [0, 5]).collect()} == want


def test_betweenness(spark):
    e = {(0, 1), (0, 2), (1, 3), (2, 3), (3, 4), (4, 5), (1, 4)}
    m = SparseMatrix(spark.createDataFrame([(a, b, 1) for a, b in e], "i bigint, j bigint, v bigint"), 6, 6)
    got = {r.vertex: r.score for r in graphs.betweenness(m, [0], 4).collect()}
    # shortest paths from 0: to 3 over 1 or 2, to 4 over 1, to 5 over 1 and 4
    assert got == {1: 2.5, 2: 0.5, 3: 0.0, 4: 1.0, 5: 0.0}


def test_plans(spark, sf):
    m = builders.part_follow(spark, sf)

    def plan(df):
        df.collect()
        return df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]

    local = plan(multiply(m, m, lowering="rowlocal", blocks=8).df)
    assert "BroadcastHashJoin" in local and "hashpartitioning(i#" in local and "hashpartitioning(i#" in local
    after = local[: local.index("BroadcastHashJoin")]
    assert "Exchange" not in after  # products are never exchanged
    fetch = lowering.rowfetch(m, m, __import__("rowproduct").functions.semiring.PLUS_TIMES, 8)
    text = plan(fetch)
    assert "Exchange" not in text[: text.index("Join")]
    assert "PushedFilters" in local or "ReadSchema: struct<l_orderkey" in local
    unsorted = plan(multiply(m, m, lowering="rowlocal").df)
    assert "Sort [" not in unsorted.split("BroadcastHashJoin")[0]


def test_or_and_and_mask(spark, ab):
    a, b = ab
    full = {(r.i, r.j) for r in multiply(a, b, semiring=OR_AND).df.collect()}
    mask = spark.createDataFrame([(0, 1), (2, 2), (3, 3)], "i bigint, j bigint")
    for low in ("joinagg", "rowlocal", "rowfetch", "splithub"):
        got = {(r.i, r.j): r.v for r in multiply(a, b, mask=mask, lowering=low).df.collect()}
        assert got == {(0, 1): 5, (2, 2): 1} and set(got) <= full


def test_rows_unsorted_input_is_refused(spark):
    from rowproduct.matrix import require_sorted

    rows = spark.createDataFrame([(0, [2, 1], [1, 1])], "i bigint, cols array<bigint>, vals array<bigint>")
    with pytest.raises(Exception, match="not sorted"):
        require_sorted(rows).collect()
    m = SparseMatrix(spark.createDataFrame([(0, 2, 1), (0, 1, 1)], "i bigint, j bigint, v bigint"), 1, 3)
    assert require_sorted(to_rows(m)).first().cols == [1, 2]


def test_block_starts_even_and_opened(spark):
    """Blocks cover all rows in order; ranges that hold a hub are opened until the bound holds."""
    import numpy as np

    rng = np.random.default_rng(5)
    work = [int(x) for x in rng.integers(0, 30, 5000)]
    work[1234], work[1235], work[4999] = 9000, 8000, 700
    rows = spark.createDataFrame(list(enumerate(work)), "i bigint, work bigint")
    for blocks, bins in ((1, 4), (7, 4), (16, 64), (16, 1 << 15)):
        starts, n = schedule.block_starts(rows, 5000, blocks, None, bins)
        assert n == blocks and starts == sorted(set(starts)) and starts[0] == 0 and len(starts) <= blocks
        got = rows.withColumn("bucket", schedule.place_of(starts)).orderBy("i").collect()
        want = np.searchsorted(starts, np.arange(5000), "right") - 1
        assert [r.bucket for r in got] == want.tolist()
        load = np.bincount(want, work)
        mean = sum(work) / blocks
        heaviest = [max(work[i] for i in np.flatnonzero(want == k)) for k in range(len(load))]
        assert all(x <= mean + max(mean / 8, h) + 1 for x, h in zip(load, heaviest, strict=True))
    assert schedule.block_starts(rows, 5000, 3, 1000)[1] == -(-sum(work) // 1000)
    assert schedule.block_starts(rows, 5000, 3, 1, most=8)[0] is None
    assert schedule.block_starts(rows.where("i < 0"), 5000, 3) == ([], 3)


def test_rowfetch_exchanges_no_products(spark, sf):
    """After the join of fetched rows, blocks add up where they are."""
    import contextlib
    import io

    m = builders.part_follow(spark, sf)
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        multiply(m, m, lowering="rowfetch").df.explain()
    above = out.getvalue().split("ShuffledHashJoin")[0]
    assert "ShuffledHashJoin" in out.getvalue() and "Exchange" not in above


def test_strong_scaling_reads_both_forms(tmp_path):
    from rowproduct.study import strong_scaling

    for text, want in (("print(int(__import__('os').environ['BENCH_CPUS']) * 2)", {1: 2.0, 3: 6.0}), ("print('noise'); print('{\"value\": 1.5}')", {1: 1.5, 3: 1.5})):
        script = tmp_path / "s.py"
        script.write_text(text)
        assert strong_scaling(str(script), [1, 3]) == want
