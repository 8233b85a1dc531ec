"""Queries of the experiments: schedules, sweeps, applications, profiles and advice."""

from __future__ import annotations

import functools

from pyspark.sql import functions as F

from ..operators import graphs
from ..operators.product import multiply
from ..plans import cost, schedule
from ..plans.advisor import CR_LIMIT, advise, recipe_table as recipe_rows, stats_of
from ..plans.cut import dropped, held
from ..plans.work import lower_bound, number_rows, prefix_sum, row_work as work_of
from ..sources import builders as src
from ..sources.synth import events_drawn, synth
from .matrices import query as _query
from .sql import cost_sql, synth_cte

QUERIES, ORACLES = {}, {}
query = functools.partial(_query, into=(QUERIES, ORACLES))
PF, P = src.part_follow, 16

_RW = "rw as (select r.i, cast(coalesce(work, 0) as bigint) work, cast(coalesce(na, 0) as bigint) na from (select unnest(range(n)) i from nparts) r left join (select x.i, sum(coalesce(nb, 0)) work, count(*) na from pf x left join (select i, count(*) nb from pf group by 1) y on x.j = y.i group by 1) w on r.i = w.i)"
_BEFORE = _RW + ", bw as (select i, work, na, cast(coalesce(sum(work) over (order by i rows between unbounded preceding and 1 preceding), 0) as bigint) b, cast(sum(work) over () as bigint) w from rw)"
_BK = _BEFORE + f", bk as (select i, work, na, b, cast(least({P - 1}, (cast(b as hugeint) * {P}) // w) as int) bucket from bw)"
_ST = _RW + f", st as (select i, work, na, cast(i * {P} // n as int) bucket from rw, nparts)"


@query("select i, work, na from rw", _RW)
def row_work(s, d):
    m = PF(s, d)
    return work_of(m, m)


@query("select i, work, b before from bw", _BEFORE)
def prefix_work(s, d):
    m = PF(s, d)
    return prefix_sum(work_of(m, m), ["i"], "work").select("i", "work", "before")


@query("select cast(t.v as bigint) value, min(i) i from (select unnest([0, 1000, 20000, 400000, 1000000000]) v) t left join bw on b >= t.v group by 1", _BEFORE)
def lower_bounds(s, d):
    m = PF(s, d)
    return lower_bound(prefix_sum(work_of(m, m), ["i"], "work"), "i", "before", [0, 1000, 20000, 400000, 10**9])


@query("select i, bucket from st", _ST)
def sched_static(s, d):
    m = PF(s, d)
    return schedule.static(work_of(m, m), m.nrows, P).select("i", "bucket")


@query(f"select i, cast(ntile({P}) over (order by i) - 1 as int) bucket from rw", _RW)
def sched_ntile(s, d):
    """Equal row counts by rank, for ids with gaps: a dense number in place of the id."""
    m = PF(s, d)
    n = number_rows(work_of(m, m), ["i"], "k")
    # As NTILE deals: the first blocks are one row larger.
    small, more = divmod(m.nrows, P)
    cut = more * (small + 1)
    b = F.when(F.col("k") < cut, F.floor(F.col("k") / (small + 1))).otherwise(more + F.floor((F.col("k") - cut) / max(1, small)))
    return n.select("i", b.cast("int").alias("bucket"))


@query("select i, bucket from bk", _BK)
def sched_balanced(s, d):
    m = PF(s, d)
    return schedule.balanced(work_of(m, m), P).select("i", "bucket")




@query("with recursive g as (select 0 chunk, cast(0 as bigint) row_lo, cast(least(n, (n + 15) // 16) as bigint) row_hi, n from (select cast(max(p_partkey) + 1 as bigint) n from part) union all select chunk + 1, row_hi, least(n, row_hi + (n - row_hi + 15) // 16), n from g where row_hi < n), pf as (select a.l_partkey i, b.l_partkey j from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and b.l_linenumber = a.l_linenumber + 1 where a.l_partkey <> b.l_partkey group by 1, 2), w as (select x.i, sum(nb) work from pf x join (select i, count(*) nb from pf group by 1) y on x.j = y.i group by 1) select cast(chunk as int) chunk, row_lo, row_hi, cast(coalesce(sum(work), 0) as bigint) work from g left join w on i >= row_lo and i < row_hi group by 1, 2, 3")
def sched_guided(s, d):
    m = PF(s, d)
    return schedule.chunk_work(work_of(m, m), schedule.chunks(m.nrows, P, "guided"))


ORACLES["sched_guided"] = ORACLES["sched_guided"][ORACLES["sched_guided"].index("with recursive"):]


@query("select cast(i // 32 as int) chunk, i // 32 * 32 row_lo, least(n, i // 32 * 32 + 32) row_hi, cast(sum(work) as bigint) work from rw, nparts group by 1, 2, 3", _RW)
def sched_dynamic(s, d):
    m = PF(s, d)
    return schedule.chunk_work(work_of(m, m), schedule.chunks(m.nrows, P, "dynamic", 32))


@query(f"select 'balanced' policy, cast(max(w) as bigint) max_work, cast(sum(w) as bigint) total, round(max(w) * {P} / sum(w), 6) imbalance from (select sum(work) w from bk group by bucket) union all select 'static', cast(max(w) as bigint), cast(sum(w) as bigint), round(max(w) * {P} / sum(w), 6) from (select sum(work) w from (select work, i * {P} // n bucket from rw, nparts) group by bucket)", _BK)
def sched_imbalance(s, d):
    m = PF(s, d)
    w = work_of(m, m)
    out = []
    for name, assigned in (("balanced", schedule.balanced(w, P)), ("static", schedule.static(w, m.nrows, P))):
        loads = assigned.groupBy("bucket").agg(F.sum("work").alias("work"))
        out.append(schedule.imbalance(loads, P).select(F.lit(name).alias("policy"), "max_work", "total", F.round("imbalance", 6).alias("imbalance")))
    return out[0].unionByName(out[1])


@query("select bucket, min(k.i) row_lo, max(k.i) row_hi, cast(sum(work) as bigint) work, max(work) max_work, max(na) heap, cast(coalesce(sum(nc), 0) as bigint) exact, case when least(max(work), max(n)) = 0 then 1 else cast(pow(2, floor(log2(least(max(work), max(n)))) + 1) as bigint) end capacity from bk k left join (select i, count(*) nc from (select x.i i, y.j j from pf x join pf y on x.j = y.i group by 1, 2) group by 1) c on k.i = c.i cross join nparts group by 1", _BK)
def buffer_plan(s, d):
    m = PF(s, d)
    return schedule.buffer_plan(m, m, P)


@query("select bucket, min(i) row_lo, max(i) row_hi, cast(sum(work) as bigint) work, max(work) max_work, max(na) max_na from bk group by 1", _BK)
def block_table(s, d):
    m = PF(s, d)
    return schedule.block_table(schedule.balanced(work_of(m, m), P))


# Sweeps over generated matrices

def _sweep(cases):
    """SQL of (kind, scale, ef, nnz, work, nnz_c) over generated matrices; ef None: every event is a draw."""
    ctes, parts = [], []
    for kind, scale, ef in cases:
        n, ef_sql = f"y_{kind}_{scale}_{ef or 'events'}", ef or f"cast((select count(*) from events) // {1 << scale} as int)"
        ctes += [synth_cte(n, scale, ef, kind), cost_sql(n, n, n)]
        parts.append(f"select '{kind}' kind, {scale} scale, {ef_sql} ef, (select count(*) from {n}) nnz, cast(sum(work) as bigint) work, cast(sum(nc) as bigint) nnz_c, round(sum(work * log2(na)), 3) t_heap, round(sum(work) + sum(nc * log2(nc)), 3) t_hash_sorted from {n}_r")
    return " union all ".join(parts), ", ".join(ctes)


def _events_ef(s, d, scale):
    return src.table(s, d, "events").count() >> scale


def _swept(s, d, cases):
    out = None
    for kind, scale, ef in cases:
        m, = held(synth(s, scale, ef, kind) if ef else events_drawn(s, d, scale, kind))
        ef = ef or _events_ef(s, d, scale)
        one = cost.costs(m, m).crossJoin(m.df.agg(F.count("*").alias("nnz"))).select(F.lit(kind).alias("kind"), F.lit(scale).alias("scale"), F.lit(ef).alias("ef"), "nnz", "work", "nnz_c", "t_heap", "t_hash_sorted")
        out = one if out is None else out.unionByName(one)
    return out


DENSITY = [(k, z, None) for k in ("uniform", "skewed") for z in (9, 8, 7)]  # the same draws on fewer places: density rises
SIZE = [(k, z, 16) for k in ("uniform", "skewed") for z in (5, 6, 7, 8)]
query(*_sweep(DENSITY), name="square_density")(lambda s, d: _swept(s, d, DENSITY))
query(*_sweep(SIZE), name="square_size")(lambda s, d: _swept(s, d, SIZE))

# Costs over our matrices: problems for profiles, trends and shares
REAL = (("part_follow", "pf"), ("supplier_follow", "sf"), ("user_next", "un"), ("follow_sym", "fs"))
_CT = ", ".join(cost_sql(c, c, c) for _, c in REAL)
_TT = ", tt as (" + " union all ".join(f"select '{n}' problem, cast(sum(work) as bigint) work, cast(sum(nc) as bigint) nnz_c, sum(work * log2(na)) h, sum(nc * log2(nc)) srt from {c}_r" for n, c in REAL) + ")"
_ML = _TT + ", ml as (select problem, 'heap' method, work / nnz_c cr, work, h cost from tt union all select problem, 'hash_sorted', work / nnz_c, work, work + srt from tt union all select problem, 'hash_unsorted', work / nnz_c, work, cast(work as double) from tt)"


def real_matrices(s, d):
    """(name, matrix) of REAL, one after another: each is stored once, deleted when the next one is asked for, and part_follow's triples also make follow_sym."""
    follow, = held(PF(s, d))
    yield "part_follow", follow
    sym, = held(src.symmetric(follow))
    dropped(follow.df)
    yield "follow_sym", sym
    dropped(sym.df)
    for name in ("supplier_follow", "user_next"):
        m, = held(src.BUILDERS[name](s, d))
        yield name, m
        dropped(m.df)


def cost_table(s, d):
    """(problem, method, cr, work, cost)"""
    out = None
    for name, m in real_matrices(s, d):
        c = cost.costs(m, m).select(F.lit(name).alias("problem"), "cr", "work", F.expr("stack(3, 'heap', t_heap, 'hash_sorted', t_hash_sorted, 'hash_unsorted', t_hash_unsorted) as (method, cost)"))
        out = c if out is None else out.unionByName(c)
    return out


@query("select problem, method, round(cr, 6) cr, work, round(cost, 3) cost from ml", _CT + _ML)
def cost_by_matrix(s, d):
    return cost_table(s, d).select("problem", "method", F.round("cr", 6).alias("cr"), "work", F.round("cost", 3).alias("cost"))


@query("select problem, work, nnz_c, round(work / nnz_c, 6) cr, case when work / nnz_c <= 2 then 'low' else 'high' end class from tt", _CT + _TT)
def compression_by_matrix(s, d):
    t = cost_table(s, d).where("method = 'heap'")
    return t.select("problem", "work", F.round(F.col("work") / F.col("cr"), 0).cast("bigint").alias("nnz_c"), F.round("cr", 6).alias("cr"), F.when(F.col("cr") <= 2, "low").otherwise("high").alias("class"))


TAUS = [1.0, 1.2, 1.5, 2.0, 3.0, 5.0]
_SC = _ML + ", sc as (select problem, method, cost / min(cost) over (partition by problem) score from ml)"


@query(f"select method, tau, round(count(*) filter (score <= tau) / count(*), 6) share from sc cross join (select unnest({TAUS}) tau) group by 1, 2", _CT + _SC)
def perf_profile(s, d):
    return cost.performance_profile(cost_table(s, d), TAUS).select("method", F.col("tau").cast("decimal(2,1)").alias("tau"), F.round("share", 6).alias("share"))


@query("select method, cast(count(*) filter (score = 1) as bigint) wins, count(*) problems, round(max(score), 4) worst from sc group by 1", _CT + _SC)
def win_share(s, d):
    return cost.win_share(cost_table(s, d)).withColumn("worst", F.round("worst", 4))


@query("select round(count(*) / sum(1 / g), 6) harmonic_mean from (select (work + srt) / work g from tt)", _CT + _TT)
def order_gain_harmonic(s, d):
    t = cost_table(s, d).groupBy("problem").pivot("method", ["hash_sorted", "hash_unsorted"]).agg(F.first("cost"))
    return cost.harmonic_mean(t.withColumn("g", F.col("hash_sorted") / F.col("hash_unsorted")), "g").select(F.round("harmonic_mean", 6).alias("harmonic_mean"))


@query("select method, round(regr_slope(work / cost, cr), 6) slope, round(regr_intercept(work / cost, cr), 6) intercept from ml group by 1", _CT + _ML)
def cr_trend(s, d):
    return cost.trend(cost_table(s, d).withColumn("rate", F.col("work") / F.col("cost")), "cr", "rate", "method")


@query("select problem, method, round(cost / min(cost) over (partition by problem), 6) score from (select l_returnflag problem, l_linestatus as method, cast(sum(cast(l_quantity as bigint)) as double) as cost from lineitem group by 1, 2)")
def profile_example(s, d):
    """Quantities by return flag and line status, as costs of methods on problems."""
    x = src.table(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("problem"), F.col("l_linestatus").alias("method"))
    return cost.scores(x.agg(F.sum(F.col("l_quantity").cast("bigint")).cast("double").alias("cost"))).select("problem", "method", F.round("score", 6).alias("score"))


@query()
def heap_ablation(s, d):
    from ..study import heap_ablation as run

    m, = held(events_drawn(s, d, 9, "skewed"))
    return s.createDataFrame(run(m, P), "setting string, imbalance double")


# Tall and skinny, searches

_COLS = "rc as (select j, cast(row_number() over (order by md5('1:' || j), j) - 1 as bigint) t from (select distinct j from {a}))"


def _tall(a, k):
    return f"select x.i i, c.t j, cast(sum(x.v * y.v) as bigint) v from {a} x join {a} y on x.j = y.i join rc c on y.j = c.j where c.t < {k} group by 1, 2", _COLS.format(a=a)


for _k in (16, 64):
    query(*_tall("tb", _k), name=f"tall_skinny_terms_{_k}")(functools.partial(lambda s, d, k: graphs.tall_skinny(src.term_bigram(s, d), k).df, k=_k))
    _b, _x = _tall("syn", _k)
    query(_b, synth_cte("syn", 9, 16, "skewed") + ", " + _x, name=f"tall_skinny_synth_{_k}")(functools.partial(lambda s, d, k: graphs.tall_skinny(synth(s, 9, 16, "skewed"), k).df, k=_k))

SOURCES = [0, 1, 2, 3, 5, 8, 13, 21]
_L0 = f"l0 as (select cast(row_number() over () - 1 as int) search, s vertex from (select unnest({SOURCES}) s))"


#: Levels that the SQL unrolls; searches of these tables end before. The queries themselves run until no search finds a new vertex.
UNROLLED = 14


def _levels(n):
    out = _L0 + ", s0 as materialized (select search, vertex, 0 as level from l0)"
    for k in range(1, n + 1):
        out += f", l{k} as materialized (select distinct f.search, e.j vertex from l{k - 1} f join pf e on e.i = f.vertex where (f.search, e.j) not in (select search, vertex from s{k - 1})), s{k} as materialized (select * from s{k - 1} union all select search, vertex, {k} from l{k})"
    return out


@query("select search, cast(vertex as bigint) vertex from l1", _levels(1))
def msbfs_step(s, d):
    f = s.createDataFrame(list(enumerate(SOURCES)), "search int, vertex bigint")
    return graphs.frontier_step(PF(s, d).df, f, f)


@query(f"select search, cast(vertex as bigint) vertex, cast(level as int) as level from s{UNROLLED}", _levels(UNROLLED))
def msbfs_levels(s, d):
    return graphs.msbfs(PF(s, d), SOURCES)


def _paths(n):
    out = _L0 + ", p0 as materialized (select search, vertex, cast(1 as bigint) paths from l0), q0 as materialized (select search, vertex, 0 as level, paths from p0)"
    for k in range(1, n + 1):
        out += f", p{k} as materialized (select f.search, e.j vertex, cast(sum(f.paths) as bigint) paths from p{k - 1} f join pf e on e.i = f.vertex where (f.search, e.j) not in (select search, vertex from q{k - 1}) group by 1, 2), q{k} as materialized (select * from q{k - 1} union all select search, vertex, {k}, paths from p{k})"
    return out


@query(f"select search, cast(vertex as bigint) vertex, cast(level as int) as level, paths from q{UNROLLED}", _paths(UNROLLED))
def bc_paths(s, d):
    return graphs.shortest_path_counts(PF(s, d), SOURCES)


@query()
def bc_scores(s, d):
    return graphs.betweenness(PF(s, d), SOURCES)


# Triangles

_RK = "rk as (select i, cast(row_number() over (order by d, i) - 1 as bigint) r from fdeg)"
_RE = _RK + ", re as (select a.r i, b.r j, v from fs join rk a on fs.i = a.i join rk b on fs.j = b.i)"
_TRI = _RE + ", tri as (select x.i a, x.j b, y.j c from re x join re y on x.j = y.i join re z on z.i = x.i and z.j = y.j where x.i < x.j and y.i < y.j)"


@query("select i, j, v from re", _RE)
def tri_reorder(s, d):
    return graphs.reorder(src.follow_sym(s, d)).df


@query("select i, j, v, case when j < i then 'L' else 'U' end part from re", _RE)
def tri_split(s, d):
    low, up = graphs.split(graphs.reorder(src.follow_sym(s, d)))
    return low.df.withColumn("part", F.lit("L")).unionByName(up.df.withColumn("part", F.lit("U")))


@query("select x.i i, y.j j, count(*) v from e x join e y on x.j = y.i where x.low and not y.low group by 1, 2", "e as (select fs.i, fs.j, (b.d, fs.j) < (a.d, fs.i) low from fs join fdeg a on fs.i = a.i join fdeg b on fs.j = b.i)")
def tri_wedges(s, d):
    return graphs.wedges(src.follow_sym(s, d)).df


@query("select count(*) triangles from tri", _TRI)
def tri_count(s, d):
    return graphs.triangle_count(src.follow_sym(s, d))


@query("select count(*) triangles from (select x.i, x.j, y.j k from co x join co y on x.j = y.i join co z on z.i = x.i and z.j = y.j where x.i < x.j and y.i < y.j)")
def tri_count_copurchase(s, d):
    return graphs.triangle_count(src.copurchase(s, d))


@query("select k.i vertex, count(*) tri from (select unnest([a, b, c]) r from tri) t join rk k on t.r = k.r group by 1", _TRI)
def tri_per_vertex(s, d):
    return graphs.triangles_by_vertex(src.follow_sym(s, d))


@query("select f.i vertex, cast(coalesce(t.n, 0) as bigint) tri, cast(d * (d - 1) / 2 as bigint) wedges from fdeg f left join (select k.i, count(*) n from (select unnest([a, b, c]) r from tri) t join rk k on t.r = k.r group by 1) t on f.i = t.i", _TRI)
def clustering_coeff(s, d):
    return graphs.clustering_coefficient(src.follow_sym(s, d))


# Clustering, labels, similarity

_MC = "lp as (select * from sf where i <> j union all select j i, j, max(v) v from sf group by j), mc as (select i, j, v / t v from (select i, j, cast(v as double) v from lp) join (select j, cast(sum(v) as double) t from lp group by 1) using (j))"
_ME = _MC + ", me as (select x.i i, y.j j, sum(x.v * y.v) v from mc x join mc y on x.j = y.i group by 1, 2)"


@query("select i, j, round(v, 6) v from me", _ME)
def mcl_expand(s, d):
    m = graphs.column_stochastic(src.supplier_follow(s, d))
    return multiply(m, m).df.select("i", "j", F.round("v", 6).alias("v"))


@query("select j, count(*) n, round(sum(v), 6) total, round(max(v), 6) top from (select j, p / sum(p) over (partition by j) v from (select i, j, p, row_number() over (partition by j order by p desc, i) r from (select i, j, round(power(v, 2.0), 12) p from me)) where r <= 20) group by 1", _ME)
def mcl_inflate(s, d):
    m = graphs.markov_round(graphs.column_stochastic(src.supplier_follow(s, d)))
    return m.df.groupBy("j").agg(F.count("*").alias("n"), F.round(F.sum("v"), 6).alias("total"), F.round(F.max("v"), 6).alias("top"))


@query("select x.i i, c.t j, round(sum(x.v * y.v), 6) v from mc x join mc y on x.j = y.i join rc c on y.j = c.j where c.t < 16 group by 1, 2", _MC + ", " + _COLS.format(a="mc"))
def mcl_subset(s, d):
    m = graphs.column_stochastic(src.supplier_follow(s, d))
    return next(graphs.subset_expand(m, 16, 16)).df.select("i", "j", F.round("v", 6).alias("v"))


@query()
def mcl_clusters(s, d):
    return graphs.markov_clusters(src.supplier_follow(s, d), 5)


@query("select i vertex, cast(label as bigint) as label from (select i, label, row_number() over (partition by i order by sum(v) desc, label) r from (select x.i, x.j % 7 as label, v from pf x) group by 1, 2) where r = 1")
def label_step(s, d):
    m = PF(s, d)
    return graphs.label_step(m, s.range(m.nrows).select(F.col("id").alias("vertex"), (F.col("id") % 7).alias("label")))


@query("select i vertex, cast(cluster as bigint) as cluster from (select i, cluster, row_number() over (partition by i order by sum(sh) desc, cluster) r from (select x.i, x.j % 7 as cluster, cast(1 / cast(d as double) as decimal(20,12)) sh from pf x join (select j, count(*) d from pf group by 1) using (j)) group by 1, 2) where r = 1")
def peer_step(s, d):
    m = PF(s, d)
    return graphs.peer_step(m, s.range(m.nrows).select(F.col("id").alias("vertex"), (F.col("id") % 7).alias("cluster")))


@query("select x.i i, y.i j, cast(sum(x.v * y.v) as bigint) dot from op x join op y on x.j = y.j and x.i < y.i group by 1, 2 having sum(x.v * y.v) >= 1500")
def order_cosine(s, d):
    return graphs.cosine_pairs(src.order_part(s, d), 1500)


@query("select x.i i, y.i j, cast(sum(x.v * y.v) as bigint) dot from dt x join dt y on x.j = y.j and x.i < y.i group by 1, 2 having sum(x.v * y.v) >= 5")
def doc_cosine(s, d):
    """Documents by their product over all terms."""
    return graphs.cosine_pairs(src.doc_term(s, d), 5)


@query("select x.i i, y.i j, cast(sum(x.v * y.v) as bigint) dot from em x join em y on x.j = y.j and x.i < y.i group by 1, 2 having sum(x.v * y.v) >= 350000000000")
def embed_cosine(s, d):
    return graphs.cosine_pairs(src.embed_rows(s, d), 350_000_000_000)


@query("select x.i i, y.i j, count(*) n from sf x join sf y on x.j = y.j and x.i < y.i group by 1, 2")
def common_neighbours(s, d):
    return graphs.common_neighbours(src.supplier_follow(s, d))


# Advice

@query("select problem, case when work / nnz_c <= 2 then 'hash' else 'inspector' end recipe, case when h < work then 'heap' else 'hash' end by_cost from tt", _CT + _TT)
def advise_real(s, d):
    rows = []
    for name, m in real_matrices(s, d):
        c = advise(stats_of(m, m), "AxA", "real", "unsorted")
        rows.append((name, c.recipe_choice, c.cost_choice))
    return s.createDataFrame(rows, "problem string, recipe string, by_cost string")


_AD = [(k, z, None) for k in ("uniform", "skewed") for z in (10, 7)]
_ab, _ax = _sweep(_AD)


@query(f"select kind, scale, ef, case when kind = 'skewed' and ef > 8 then 'hash' else 'heap' end recipe, case when t_heap < t_hash_sorted then 'heap' else 'hash' end by_cost from ({_ab})", _ax)
def advise_synth(s, d):
    rows = []
    for kind, scale, _ in _AD:
        m, ef = events_drawn(s, d, scale, kind), _events_ef(s, d, scale)
        st = stats_of(m, m)
        c = advise(type(st)(**{**vars(st), "skew": kind}), "AxA", "synthetic", "sorted", edge_factor=ef)
        rows.append((kind, scale, ef, c.recipe_choice, c.cost_choice))
    return s.createDataFrame(rows, "kind string, scale int, ef int, recipe string, by_cost string")


_RB = cost_sql("pf", "pf", "c") + f", rb as (select cast(i * {P} // n as int) bucket, sum(work) / sum(nc) cr from c_r, nparts group by 1)"


@query("select bucket, row_order, case when cr <= 2 then 'low' else 'high' end as class, case when row_order = 'unsorted' and cr > 2 then 'inspector' else 'hash' end as method from rb, (values ('sorted'), ('unsorted')) o(row_order)", _RB)
def recipe_table(s, d):
    """The rules' methods for each block of rows of a square, by its compression."""
    m, = held(PF(s, d))
    r = cost.row_costs(m, m).groupBy(schedule.static_block(m.nrows, P).alias("bucket")).agg((F.sum("work") / F.sum("nc")).alias("cr"))
    r = r.withColumn("class", F.when(F.col("cr") <= CR_LIMIT, "low").otherwise("high"))
    return r.join(F.broadcast(recipe_rows(s).where("source = 'real' and op = 'AxA'")), "class").select("bucket", "row_order", "class", "method")


# Probes of the machine: times, so rows only

@query()
def alloc_probe(s, d):
    from ..study import alloc_probe as run

    ids = src.table(s, d, "events").select("event_id")
    return run(ids, 1).withColumn("mode", F.lit("single")).unionByName(run(ids, 8).withColumn("mode", F.lit("parallel")))


@query()
def stanza_probe(s, d):
    from ..study import stanza_probe as run

    out = run(s, 8, 1 << 24)
    for n in (64, 512, 4096):
        out = out.unionByName(run(s, n, 1 << 24))
    return out


@query()
def schedule_probe(s, d):
    from ..study import schedule_probe as run

    return s.createDataFrame([(p, run(src.table(s, d, "events").select("event_id"), p, 8)) for p in ("static", "dynamic", "guided")], "policy string, seconds double")
