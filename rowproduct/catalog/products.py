"""Queries of the products: accumulators, phases, lowerings, semirings, baselines."""

from __future__ import annotations

import functools

from pyspark.sql import functions as F

from ..functions import semiring as sr
from ..operators import algebra as alg
from ..operators import baselines
from ..operators.product import Inspector, multiply, numeric, symbolic, symbolic_approx
from ..plans import cost
from ..plans.cut import held
from ..sources import builders as src
from .matrices import query as _query
from .sql import cost_sql, product

QUERIES, ORACLES = {}, {}
query = functools.partial(_query, into=(QUERIES, ORACLES))
PF, SQUARE = src.part_follow, product("pf", "pf")


def squared(build, cte, name, **options):
    query(product(cte, cte), name=name)(lambda s, d: (lambda m: multiply(m, m, **options).df)(build(s, d)))


for _n, _c in (("part_follow", "pf"), ("supplier_follow", "sf"), ("user_next", "un")):
    squared(src.BUILDERS[_n], _c, f"square_{_n}")

# Accumulators, one product for all
squared(PF, "pf", "acc_hash", accumulator="hash")
squared(PF, "pf", "acc_hash_one_phase", accumulator="hash", phases=1)
squared(PF, "pf", "acc_hash_sorted", accumulator="hash", order="sorted")
squared(PF, "pf", "acc_chunk8", accumulator="chunk", lanes=8)
squared(PF, "pf", "acc_chunk16", accumulator="chunk", lanes=16)
squared(PF, "pf", "acc_heap", accumulator="heap")
squared(PF, "pf", "acc_dense", accumulator="dense")
squared(PF, "pf", "acc_sortagg", accumulator="sortagg", order="sorted")
squared(PF, "pf", "acc_advised", accumulator="advised")
squared(PF, "pf", "acc_advised_sorted", accumulator="advised", order="sorted")
squared(PF, "pf", "acc_static_rows", accumulator="hash", schedule="static")

# Lowerings
for _low in ("joinagg", "rowlocal", "rowfetch", "splithub"):
    squared(PF, "pf", f"low_{_low}", lowering=_low)


@query(SQUARE)
def low_splithub_small_target(s, d):
    from ..plans.lowering import splithub

    m = PF(s, d)
    return splithub(m, m, sr.PLUS_TIMES, target=100)


# Phases
@query("select i, count(*) nnz from (select x.i i, y.j j from pf x join pf y on x.j = y.i group by 1, 2) group by 1")
def symbolic_sizes(s, d):
    m = PF(s, d)
    return symbolic(m, m)


@query(name="symbolic_approx")
def symbolic_approx_sizes(s, d):
    m = PF(s, d)
    return symbolic_approx(m, m)


@query(SQUARE)
def one_vs_two_phase(s, d):
    m = PF(s, d)
    two = multiply(m, m, lowering="joinagg").df
    structure = two.select("i", "j")
    return numeric(m, m, structure)


@query("select x.i i, y.j j, cast(sum(x.v * x.v * y.v) as bigint) v from pf x join pf y on x.j = y.i group by 1, 2")
def numeric_reuse(s, d):
    """Patterns inspected once, then multiplied with other values."""
    m = PF(s, d)
    return Inspector(m, m).execute(alg.apply(m, lambda v: v * v), m).df


# Semirings and masks
SEMIRINGS = {"or_and": (sr.OR_AND, "cast(1 as bigint)"), "min_plus": (sr.MIN_PLUS, "min(x.v + y.v)"), "max_times": (sr.MAX_TIMES, "max(x.v * y.v)"), "plus_pair": (sr.PLUS_PAIR, "count(*)")}
for _n, (_r, _e) in SEMIRINGS.items():
    query(product("pf", "pf", _e), name=f"product_{_n}")(functools.partial(lambda s, d, r: (lambda m: multiply(m, m, semiring=r).df)(PF(s, d)), r=_r))


@query("select x.i i, y.j j, cast(sum(x.v * y.v) as bigint) v from pf x join pf y on x.j = y.i join co m on m.i = x.i and m.j = y.j group by 1, 2")
def product_masked(s, d):
    m = PF(s, d)
    return multiply(m, m, mask=src.copurchase(s, d).df).df


@query("select x.i i, y.j j, cast(sum(x.v * y.v) as bigint) v from pf x join pf y on x.j = y.i where not exists (select 1 from pf m where m.i = x.i and m.j = y.j) group by 1, 2")
def product_unvisited(s, d):
    """The complement of a mask."""
    m = PF(s, d)
    return multiply(m, m).df.join(m.df.select("i", "j"), ["i", "j"], "left_anti")


# Shapes
@query(product("op", "opt"), "opt as (select j i, i j, v from op)")
def gram_rows(s, d):
    return alg.gram_rows(src.order_part(s, d)).df


@query(product("opt", "op"), "opt as (select j i, i j, v from op)")
def gram_cols(s, d):
    return alg.gram_cols(src.order_part(s, d)).df


@query("select a.j i, b.j j, cast(sum(x.v) as bigint) v from sf x join sn a on x.i = a.i join sn b on x.j = b.i group by 1, 2")
def galerkin(s, d):
    return alg.galerkin(src.supp_nation(s, d), src.supplier_follow(s, d)).df


@query("select x.i i, y.j j, cast(sum(x.v * y.v) as bigint) v from (" + product("sf", "sf") + ") x join sf y on x.j = y.i group by 1, 2")
def power3(s, d):
    return alg.power(src.supplier_follow(s, d), 3).df


@query("select x.i i, y.j j, cast(sum(x.v * y.v) as bigint) v from cp x join ps y on x.j = y.i group by 1, 2")
def product_rectangular(s, d):
    return multiply(*held(src.cust_part(s, d), src.part_supp(s, d))).df


@query("select x.i i, y.j j, cast(sum(x.q * y.v) as decimal(38,2)) v from (select i, j, cast(v as decimal(18,2)) * cast(0.25 as decimal(3,2)) q from pf) x join pf y on x.j = y.i group by 1, 2")
def product_decimal(s, d):
    """Quarters as decimals of two places: exact, whatever scale the engines carry inside."""
    m = PF(s, d)
    return multiply(alg.apply(m, lambda v: (v.cast("decimal(12,2)") * F.lit("0.25").cast("decimal(3,2)")).cast("decimal(18,2)")), m).df.select("i", "j", F.col("v").cast("decimal(38,2)").alias("v"))


# Baselines
@query(SQUARE)
def baseline_plain(s, d):
    m = PF(s, d)
    return baselines.plain(m, m)


@query(SQUARE)
def baseline_plain_sorted(s, d):
    m = PF(s, d)
    return baselines.plain(m, m, "sorted")


@query(SQUARE)
def baseline_pooled(s, d):
    m = PF(s, d)
    return baselines.pooled(m, m, pool=256)


@query(SQUARE)
def baseline_expand_sort(s, d):
    m = PF(s, d)
    return baselines.expand_sort(m, m)


@query(product("sf", "sf"))
def baseline_blocks(s, d):
    m = src.supplier_follow(s, d)
    return baselines.blocks(m, m)


# Costs
def _cost(cte):
    t = f"select cast(sum(work) as bigint) work, cast(sum(nc) as bigint) nnz_c, sum(work) / sum(nc) cr, round(sum(work * log2(na)), 3) t_heap, round(sum(work) + sum(nc * log2(nc)), 3) t_hash_sorted, round(cast(sum(work) as double), 3) t_hash_unsorted from c_r"
    return t, cost_sql(cte, cte, "c")


for _n, _c in (("part_follow", "pf"), ("supplier_follow", "sf"), ("user_next", "un")):
    query(*_cost(_c), name=f"cost_{_n}")(functools.partial(lambda s, d, f: (lambda m: cost.costs(m, m))(f(s, d)), f=src.BUILDERS[_n]))


@query("select max(na) heap, max(work) hash, max(n) dense from c_w, nparts", cost_sql("pf", "pf", "c"))
def accumulator_memory(s, d):
    m = PF(s, d)
    return cost.accumulator_memory(m, m)


@query("select run_len, run_len * 12 run_bytes, cast(sum(reads) as bigint) reads from (select j, count(*) reads from pf group by 1) a join (select i, count(*) run_len from pf group by 1) b on a.j = b.i group by 1")
def stanza_profile(s, d):
    m = PF(s, d)
    return cost.stanza_profile(m, m)


@query()
def probe_stats(s, d):
    m = PF(s, d)
    return cost.probe_stats(m, m)
