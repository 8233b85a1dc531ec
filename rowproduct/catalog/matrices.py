"""Queries that build, reshape, store and combine matrices."""

from __future__ import annotations

import functools

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions import tables
from ..functions.kernels import table_capacity
from ..matrix import clean, densify, dot_packed, map_row_add, permute_columns, require_sorted, shuffle_within_rows, to_map_rows, to_rows, to_triples
from ..operators import algebra as alg
from ..plans.work import checked_broadcast, number_rows
from ..sources import builders as src
from ..sources import files
from .sql import product, synth_cte, triples, with_ctes

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None, extra: str = "", name: str | None = None, into=(QUERIES, ORACLES)):
    def keep(f):
        n = name or f.__name__
        into[0][n] = f
        if sql:
            into[1][n] = with_ctes(sql, extra)
        return f

    return keep


NAMES = {"order_part": "op", "part_supp": "ps", "cust_part": "cp", "part_follow": "pf", "supplier_follow": "sf", "copurchase": "co", "follow_sym": "fs", "user_next": "un", "user_type": "ut",
         "doc_term": "dt", "term_bigram": "tb", "page_anchor": "pa", "embed_rows": "em", "nation_region": "nr", "cust_nation": "cn", "supp_nation": "sn", "cust_month": "cm", "user_propkey": "up"}
for _name, _cte in NAMES.items():
    query(triples(_cte), name=f"build_{_name}")(functools.partial(lambda s, d, f: f(s, d).df, f=src.BUILDERS[_name]))


def text_of(c):
    return F.concat_ws(",", F.transform(c, lambda x: x.cast("string")))


PF = src.part_follow


@query("select i, string_agg(cast(j as varchar), ',' order by j) cols, string_agg(cast(v as varchar), ',' order by j) vals from pf group by 1", name="to_rows")
def to_rows_sorted(s, d):
    r = require_sorted(to_rows(PF(s, d)))
    return r.select("i", text_of("cols").alias("cols"), text_of("vals").alias("vals"))


@query(triples("pf"), name="to_triples")
def to_triples_back(s, d):
    return to_triples(shuffle_within_rows(to_rows(PF(s, d)), 3))


@query("select r.i i, cast(coalesce(n, 0) as bigint) nnz, cast(coalesce(sum(n) over (order by r.i rows between unbounded preceding and 1 preceding), 0) as bigint) ptr from (select unnest(range(n)) i from nparts) r left join (select i, count(*) n from pf group by 1) x on r.i = x.i")
def row_pointers(s, d):
    return alg.row_pointers(PF(s, d))


@query(triples("sf"), name="to_map_rows")
def to_map_rows_back(s, d):
    return to_map_rows(src.supplier_follow(s, d)).select("i", F.explode("row").alias("j", "v"))


@query("select i, j, cast(sum(v) as bigint) v from (select * from sf union all select j i, i j, v from sf) group by 1, 2", name="map_row_add")
def map_row_sum(s, d):
    m = src.supplier_follow(s, d)
    return map_row_add(to_map_rows(m), to_map_rows(m.transpose())).select("i", F.explode("row").alias("j", "v"))


@query("select term, cast(row_number() over (order by term) - 1 as bigint) id from (select distinct term from dterm)")
def encode_ids(s, d):
    return number_rows(src.doc_terms(s, d).select("term").distinct(), ["term"])


@query("select j i, i j, v from pf")
def transpose(s, d):
    return PF(s, d).transpose().df


@query("select n.i i, string_agg(cast(coalesce(v, 0) as varchar), ',' order by r.j) cells from (select distinct i from nr) n cross join (select unnest(range(5)) j) r left join nr on nr.i = n.i and nr.j = r.j group by 1", name="densify")
def dense_rows(s, d):
    return densify(src.nation_region(s, d)).select("i", text_of("row").alias("cells"))


@query("select i, b.to_j j, v from pf join (select h.j, l.j to_j from (select j, row_number() over (order by md5('7:' || j), j) k from (select distinct j from pf)) h join (select j, row_number() over (order by j) k from (select distinct j from pf)) l using (k)) b on pf.j = b.j")
def permuted_columns(s, d):
    return permute_columns(PF(s, d), 7).df


@query("select user_id i, cast(id as bigint) j, cast(sum(case when event_id % 10 = 1 then 0 else event_id % 7 end) as bigint) v from events join ety on event_type = name where user_id is not null and event_type <> 'refund' and event_id % 11 <> 3 and event_id % 10 <> 0 group by 1, 2")
def clean_triples(s, d):
    """Events as triples with gaps of every kind: no row, no column, no value, values of 0, repeated places."""
    e = F.col("event_id")
    raw = src.table(s, d, "events").select(F.when(e % 11 != 3, F.col("user_id")).alias("i"), F.when(F.col("event_type") != "refund", src.event_type_id()).alias("j"),
                                           F.when(e % 10 == 1, F.lit(0).cast("bigint")).when(e % 10 != 0, e % 7).alias("v"))
    return clean(raw)


@query("select i, j, 3 * v v from pf")
def scale_values(s, d):
    return alg.apply(PF(s, d), lambda v: v * 3).df


@query("select i, j, v from pf where v >= 30")
def prune_below(s, d):
    return alg.prune_below(PF(s, d), 30).df


@query("select i, j, v from un where i <> j")
def strip_diagonal(s, d):
    return alg.strip_diagonal(src.user_next(s, d)).df


@query("select i, j, v from pf where i >= 10 and i < 60")
def slice_rows(s, d):
    return alg.slice_rows(PF(s, d), 10, 60).df


@query("select i, k.t j, v from pf join (select j, cast(row_number() over (order by md5('1:' || j), j) - 1 as bigint) t from (select distinct j from pf)) k using (j) where k.t < 16")
def column_subset(s, d):
    from ..operators.graphs import random_columns

    return random_columns(PF(s, d), 16).df


@query("select i, j, cast(sum(v) as bigint) v from (select * from pf union all select * from fs) group by 1, 2")
def ewise_add(s, d):
    return alg.ewise_add(PF(s, d), src.follow_sym(s, d)).df


@query("select i, j, cast(sum(v) as bigint) v from (select * from pf union all select i, j, -v from fs) group by 1, 2")
def ewise_subtract(s, d):
    return alg.ewise_add(PF(s, d), src.follow_sym(s, d), -1).df


@query("select i, j, x.v * y.v v from pf x join co y using (i, j)")
def ewise_mult(s, d):
    return alg.ewise_mult(PF(s, d), src.copurchase(s, d)).df


@query("select i, j, v * v v from pf")
def apply_power(s, d):
    return alg.apply(PF(s, d), lambda v: F.pow(v, F.lit(2)).cast("bigint")).df


@query("select i, j, cast(1 as bigint) v from pf")
def to_pattern(s, d):
    return alg.apply(PF(s, d), lambda v: F.lit(1).cast("bigint")).df


@query("select i, j, (i + 1) * v v from pf")
def scale_rows(s, d):
    m = PF(s, d)
    return alg.scale_rows(m, s.range(m.nrows).select(F.col("id").alias("i"), (F.col("id") + 1).alias("d"))).df


for _by in "ij":
    query(f"select i, j, v, cast(total as bigint) total, round(v / total, 6) share from pf join (select {_by}, sum(v) total from pf group by 1) using ({_by})", name=f"normalise_{'rows' if _by == 'i' else 'columns'}")(
        functools.partial(lambda s, d, by: alg.normalise(PF(s, d), by).withColumn("share", F.round("share", 6)), by=_by))


@query("select i, cast(sum(v * (j + 1)) as bigint) y from pf group by 1")
def spmv(s, d):
    m = PF(s, d)
    return alg.spmv(m, s.range(m.ncols).select(F.col("id").alias("j"), (F.col("id") + 1).alias("x")))


@query("select j, cast(sum(v * (i + 1)) as bigint) y from pf group by 1")
def vecmat(s, d):
    m = PF(s, d)
    return alg.vecmat(s.range(m.nrows).select(F.col("id").alias("i"), (F.col("id") + 1).alias("x")), m)


@query("select x.i * 25 + y.i i, x.j * 5 + y.j j, x.v * y.v v from nr x cross join nr y")
def kron_small(s, d):
    m = src.nation_region(s, d)
    return alg.kron(m, m).df


# Sources and sinks

def _scratch(s, name):
    import uuid

    from ..plans.cut import cut

    if s.sparkContext.getCheckpointDir() is None:
        cut(s.range(1))
    return f"{s.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


for _fmt in ("csv", "json", "orc"):
    def _round(s, d, fmt):
        path = _scratch(s, fmt)
        files.write_triples(PF(s, d).df, path, fmt)
        return files.read_triples(s, path, fmt)

    query(triples("pf"), name=f"io_roundtrip_{_fmt}")(functools.partial(_round, fmt=_fmt))


@query("select i, j, v, cast(n as bigint) nrows from pf, nparts")
def io_coordinate_text(s, d):
    path = _scratch(s, "coordinate")
    files.write_coordinate_text(PF(s, d), path)
    m = files.read_coordinate_text(s, f"{path}/head", f"{path}/entries")
    return m.df.withColumn("nrows", F.lit(m.nrows).cast("bigint"))


@query("select i, j, v, cast(i * 8 // n as int) bucket from pf, nparts")
def sink_row_blocks(s, d):
    from ..plans.schedule import static

    m, path = PF(s, d), _scratch(s, "blocks")
    files.write_row_blocks(static(m.df, m.nrows, 8), path)
    return s.read.parquet(path).select("i", "j", "v", F.col("bucket").cast("int").alias("bucket"))


@query("select i, j, v from syn", synth_cte("syn", 7, None, "skewed"))
def scan_synth(s, d):
    """Every event is a draw, placed in Python as it is scanned."""
    from ..sources.synth import scan_drawn

    return scan_drawn(src.table(s, d, "events").select("event_id"), 7, "skewed")


for _kind in ("uniform", "skewed"):
    def _syn(s, d, kind):
        from ..sources.synth import synth

        return synth(s, 8, 8, kind).df

    query("select i, j, v from syn", synth_cte("syn", 8, 8, _kind), name=f"synth_{_kind}")(functools.partial(_syn, kind=_kind))


# Functions

@query("select w, case when w = 0 then 1 else cast(pow(2, floor(log2(w)) + 1) as bigint) end capacity from (select distinct work w from (select x.i, cast(sum(n) as bigint) work from pf x join (select i, count(*) n from pf group by 1) y on x.j = y.i group by 1))", name="table_capacity")
def table_capacities(s, d):
    from ..plans.work import row_work

    m = PF(s, d)
    w = row_work(m, m, all_rows=False).select(F.col("work").alias("w")).where("w > 0").distinct()
    cap = F.expr("shiftleft(cast(1 as bigint), length(bin(w)))")
    assert table_capacity(4, 4) == 8
    return w.select("w", cap.cast("bigint").alias("capacity"))


@query("select i, j, (j * 2654435761) & 1023 slot, (j * 2654435761) & 1023 slot_udf, bit_count(j) bits from pf", name="udf_slot")
def slots(s, d):
    m = PF(s, d).df.withColumn("cap", F.lit(1024).cast("bigint"))
    return m.select("i", "j", tables.slot("j", "cap").alias("slot"), tables.slot_udf("j", "cap").alias("slot_udf"), F.bit_count("j").cast("tinyint").alias("bits"))


@query("select i, cast(sum(v) as bigint) v from sf group by 1")
def udaf_merge_rows(s, d):
    return src.supplier_follow(s, d).df.groupBy("i").agg(tables.merge_rows("v").alias("v"))


@query(triples("sf"))
def udtf_expand_row(s, d):
    tables.register(s)
    to_rows(src.supplier_follow(s, d)).createOrReplaceTempView("packed_rows")
    return s.sql("select p.i, e.j, e.v from packed_rows p, lateral expand_row(p.cols, p.vals) e")


@query("select i, j, v from syn", synth_cte("syn", 6, 8, "uniform"), name="udtf_synth")
def udtf_synth_edges(s, d):
    tables.register(s)
    return s.sql("select i, j, count(*) v from synth_edges(6, 8, 'uniform') group by i, j")


@query(product("pf", "pf"))
def sql_product(s, d):
    PF(s, d).df.createOrReplaceTempView("follow_triples")
    return tables.sql_product(s, "follow_triples", "follow_triples")


@query("select x.i a, y.i b, cast(sum(x.v * y.v) as bigint) dot from em x join em y on x.j = y.j and y.i = x.i + 1 group by 1, 2", name="dot_packed")
def dot_packed_rows(s, d):
    r = to_rows(src.embed_rows(s, d))
    nxt = r.select((F.col("i") - 1).alias("i"), F.col("i").alias("b"), F.col("cols").alias("c2"), F.col("vals").alias("v2"))
    return r.join(nxt, "i").select(F.col("i").alias("a"), "b", dot_packed("cols", "vals", "c2", "v2").alias("dot"))


@query("select i, count(*) n, cast(sum(case when v > 1 then 1 else 0 end) as bigint) big, min(j) first_j, max(j) last_j, cast(sum(v) as bigint) total from sf group by 1")
def array_functions(s, d):
    r = to_rows(src.supplier_follow(s, d))
    return r.select("i", F.size("cols").cast("bigint").alias("n"), F.size(F.filter("vals", lambda v: v > 1)).cast("bigint").alias("big"), F.element_at("cols", 1).alias("first_j"), F.element_at("cols", -1).alias("last_j"),
                    F.aggregate("vals", F.lit(0).cast("bigint"), lambda a, v: a + v).alias("total"))


@query("select i, '{\"n\":' || count(*) || ',\"total\":' || cast(sum(v) as bigint) || '}' stats from sf group by 1")
def stats_json(s, d):
    return src.supplier_follow(s, d).df.groupBy("i").agg(F.to_json(F.struct(F.count("*").alias("n"), F.sum("v").alias("total"))).alias("stats"))


# Set operations, order, top k

for _op, _sql in (("union", "union"), ("intersect", "intersect"), ("except", "except")):
    def _set(s, d, op):
        a, b = PF(s, d).df.select("i", "j"), src.copurchase(s, d).df.select("i", "j")
        return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: b.exceptAll(a).distinct()}[op]()

    query({"union": "select i, j from pf union select i, j from co", "intersect": "select i, j from pf intersect select i, j from co", "except": "select i, j from co except select i, j from pf"}[_op], name=f"set_{_op}_pattern")(functools.partial(_set, op=_op))


@query("select i, j, v, row_number() over (partition by i order by j) place from pf")
def order_sorted(s, d):
    m = PF(s, d).sorted_rows(8)
    packed = m.df.groupBy("i").agg(F.array_sort(F.collect_list(F.struct("j", "v"))).alias("r"))
    return packed.select("i", F.posexplode("r").alias("p", "e")).select("i", "e.j", "e.v", (F.col("p") + 1).cast("bigint").alias("place"))


@query("select i, j, v from (select *, row_number() over (partition by i order by v desc, j) r from pf) where r <= 3")
def topk_per_row(s, d):
    return alg.topk_per_row(PF(s, d), 3).df


@query("select i, j, v from pf order by v desc, i, j limit 20")
def topk_global(s, d):
    return PF(s, d).df.orderBy(F.desc("v"), "i", "j").limit(20)


@query("select i, j, v from pf order by v desc, i, j limit 10 offset 10")
def limit_offset(s, d):
    return PF(s, d).df.orderBy(F.desc("v"), "i", "j").offset(10).limit(10)


# Joins

for _hint in ("shuffle_hash", "merge", "broadcast"):
    def _hinted(s, d, hint):
        from ..functions.semiring import PLUS_TIMES
        from ..plans.lowering import joinagg

        m = PF(s, d)
        if hint == "broadcast" and checked_broadcast(m.df) is None:
            hint = None  # beyond the broadcast's bound both sides are exchanged
        return joinagg(m, m, PLUS_TIMES, hint=hint)

    query(product("pf", "pf"), name=f"join_{_hint}")(functools.partial(_hinted, hint=_hint))

_BLOCKS = "blk as (select b, b * 64 lo, b * 64 + 64 hi from range((select max(i) // 64 + 1 from pf)) t(b))"


def _cover(s, m):
    """(b, lo, hi): as many blocks of 64 ids as the matrix has rows for."""
    return s.range(-(-m.nrows // 64)).select(F.col("id").cast("int").alias("b"), (F.col("id") * 64).alias("lo"), (F.col("id") * 64 + 64).alias("hi"))


@query("select cast(b as int) b, count(*) rows, cast(sum(v) as bigint) total from blk join pf on i >= lo and i < hi group by 1", _BLOCKS)
def join_nested_buckets(s, d):
    """A range join of all rows with a small table of blocks; beyond the broadcast's bound, by grid cell."""
    m = PF(s, d)
    small = checked_broadcast(_cover(s, m), -(-m.nrows // 64))
    if small is None:
        return join_range_blocks(s, d)
    return m.df.join(small, (F.col("i") >= F.col("lo")) & (F.col("i") < F.col("hi"))).groupBy("b").agg(F.count("*").alias("rows"), F.sum("v").alias("total"))


@query("select cast(b as int) b, count(*) rows, cast(sum(v) as bigint) total from blk join pf on i >= lo and i < hi group by 1", _BLOCKS)
def join_range_blocks(s, d):
    """The same range join as an equi-join on the grid cell that both sides fall in."""
    m, grid = PF(s, d), 64
    cells = _cover(s, m).withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / grid), F.floor((F.col("hi") - 1) / grid))))
    return m.df.withColumn("cell", F.floor(F.col("i") / grid)).join(cells, "cell").where("i >= lo and i < hi").groupBy("b").agg(F.count("*").alias("rows"), F.sum("v").alias("total"))


@query("select event_id, last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) last_purchase from events")
def join_asof_edges(s, d):
    """As-of: each event with its user's latest purchase before it, in one pass over one sorted union."""
    e = src.table(s, d, "events")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return e.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))


@query("select a.event_id, count(b.event_id) n from events a left join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour group by 1")
def join_interval_events(s, d):
    """Events of the same user within an hour after: an equi-join on user and hour cell, then the exact bounds."""
    e = src.table(s, d, "events").select("event_id", "user_id", "ts", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("t2"), "h")
    a = e.withColumn("h", F.explode(F.array("h", F.col("h") + F.expr("interval 1 hour"))))
    hit = a.join(b, ["user_id", "h"]).where("t2 > ts and t2 <= ts + interval 1 hour").groupBy("event_id").agg(F.count("b").alias("n"))
    return e.select("event_id").join(hit, "event_id", "left").select("event_id", F.coalesce("n", F.lit(0)).cast("bigint").alias("n"))


@query("select coalesce(x.i, y.i) i, coalesce(x.j, y.j) j, x.v a, y.v b from pf x full join co y on x.i = y.i and x.j = y.j")
def join_outer_structure(s, d):
    return PF(s, d).df.withColumnRenamed("v", "a").join(src.copurchase(s, d).df.withColumnRenamed("v", "b"), ["i", "j"], "full")


@query("select i, j, v from pf where i in (select j from op)")
def join_semi_needed_rows(s, d):
    """The rows that all orders need."""
    need = src.order_part(s, d).df.select(F.col("j").alias("i")).distinct()
    return PF(s, d).df.join(need, "i", "left_semi")


@query("select cast(p_partkey as bigint) i from part where p_partkey not in (select i from pf)")
def join_anti_empty_rows(s, d):
    m = PF(s, d)
    return s.range(m.nrows).withColumnRenamed("id", "i").join(m.df.select("i"), "i", "left_anti")
