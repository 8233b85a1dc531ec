"""SQL of the same matrices and sums, written for DuckDB apart from the engine."""

from __future__ import annotations

import re

CTES = {
    "op": "select l_orderkey i, l_partkey j, cast(sum(cast(l_quantity as bigint)) as bigint) v from lineitem group by 1, 2",
    "ps": "select l_partkey i, l_suppkey j, cast(sum(cast(l_quantity as bigint)) as bigint) v from lineitem group by 1, 2",
    "cp": "select o_custkey i, l_partkey j, cast(sum(cast(l_quantity as bigint)) as bigint) v from lineitem join orders on l_orderkey = o_orderkey group by 1, 2",
    "pf": "select a.l_partkey i, b.l_partkey j, cast(sum(cast(a.l_quantity as bigint)) as bigint) v from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and b.l_linenumber = a.l_linenumber + 1 where a.l_partkey <> b.l_partkey group by 1, 2",
    "sf": "select a.l_suppkey i, b.l_suppkey j, count(*) v from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and b.l_linenumber = a.l_linenumber + 1 where a.l_suppkey <> b.l_suppkey group by 1, 2",
    "co": "select distinct a.l_partkey i, b.l_partkey j, cast(1 as bigint) v from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey where a.l_partkey <> b.l_partkey",
    "fs": "select i, j, cast(1 as bigint) v from (select i, j from pf union select j, i from pf)",
    "un": "select i, j, count(*) v from (select user_id i, lead(user_id) over (order by ts, event_id) j from events) where j is not null group by 1, 2",
    "ety": "select * from (values ('click', 0), ('purchase', 1), ('refund', 2), ('signup', 3), ('view', 4)) t(name, id)",
    "ut": "select user_id i, cast(id as bigint) j, count(*) v from events join ety on event_type = name group by 1, 2",
    "tok": "select doc_id, lang, list_filter(regexp_extract_all(lower(text), '[a-z]+'), lambda x: length(x) > 2) w from documents",
    "dterm": "select doc_id i, term, count(*) v from (select doc_id, unnest(w) term from tok) group by 1, 2",
    "dt": "select i, cast('0x' || substr(md5(term), 1, 15) as bigint) j, v from dterm",
    "bg": "select a, b, count(*) v from (select unnest(list_zip(w[1:len(w) - 1], w[2:])) p from tok where lang = 'en' and len(w) > 1), lateral (select p[1] a, p[2] b) group by 1, 2",
    "tb": "select cast('0x' || substr(md5(a), 1, 15) as bigint) i, cast('0x' || substr(md5(b), 1, 15) as bigint) j, v from bg",
    "pa": "select page_id i, cast('0x' || substr(md5(h), 1, 15) as bigint) j, count(*) v from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) h from pages) group by 1, 2",
    "em": "select vec_id i, cast(generate_subscripts(embedding, 1) - 1 as bigint) j, cast(floor(cast(unnest(embedding) as double) * 1000000 + 0.5) as bigint) v from embeddings",
    "nr": "select cast(n_nationkey as bigint) i, cast(n_regionkey as bigint) j, cast(1 as bigint) v from nation",
    "cn": "select c_custkey i, cast(c_nationkey as bigint) j, cast(1 as bigint) v from customer",
    "sn": "select s_suppkey i, cast(s_nationkey as bigint) j, cast(1 as bigint) v from supplier",
    "cm": "select o_custkey i, cast((year(o_orderdate) - 1992) * 12 + month(o_orderdate) - 1 as bigint) j, count(*) v from orders group by 1, 2",
    "up": "select user_id i, cast(json_extract_string(props, '$.k') as bigint) j, count(*) v from events where json_extract_string(props, '$.k') is not null group by 1, 2",
    "nparts": "select cast(max(p_partkey) + 1 as bigint) n from part",
    "fdeg": "select i, count(*) d from fs group by 1",
    "cdeg": "select i, count(*) d from co group by 1",
}


def synth_sql(scale: int, ef: int | None, kind: str) -> str:
    """ef None: every event is a draw."""
    a, b, c = (0.25, 0.25, 0.25) if kind == "uniform" else (0.57, 0.19, 0.19)
    edges = f"range({(1 << scale) * ef}) t(e)" if ef else "(select event_id e from events)"
    return (
        f"select cast(sum(r * (1 << ({scale} - 1 - l))) as bigint) i, cast(sum(q * (1 << ({scale} - 1 - l))) as bigint) j from ("
        f"select e, l, cast(u >= {a} + {b} as int) r, cast((u >= {a} and u < {a} + {b}) or u >= {a} + {b} + {c} as int) q from ("
        f"select e, l, cast('0x' || substr(md5(e || ':' || l), 1, 7) as bigint) / cast(268435456 as double) u from {edges}, range({scale}) s(l))) group by e"
    )


def synth_cte(name: str, scale: int, ef: int | None, kind: str) -> str:
    return f"{name} as (select i, j, count(*) v from ({synth_sql(scale, ef, kind)}) group by 1, 2)"


def with_ctes(body: str, extra: str = "") -> str:
    """body after the common tables that it names, and those they name."""
    need: list[str] = []

    def visit(text: str) -> None:
        for name in CTES:
            if name not in need and re.search(rf"\b(from|join|,)\s+{name}\b", text):
                visit(CTES[name])
                if name not in need:
                    need.append(name)

    visit(body + " " + extra)
    parts = [f"{n} as ({CTES[n]})" for n in need] + ([extra] if extra else [])
    return (f"with {', '.join(parts)} " if parts else "") + body


def product(a: str, b: str, value: str = "cast(sum(x.v * y.v) as bigint)", where: str = "") -> str:
    return f"select x.i i, y.j j, {value} v from {a} x join {b} y on x.j = y.i {where} group by 1, 2"


def triples(a: str) -> str:
    return f"select i, j, v from {a}"


def cost_sql(a: str, b: str, tag: str) -> str:
    """Tables {tag}_r(i, work, na, nc): sizes in separate groupings."""
    return (
        f"{tag}_b as (select i, count(*) nb from {b} group by 1), "
        f"{tag}_w as (select x.i, cast(sum(coalesce(nb, 0)) as bigint) work, count(*) na from {a} x left join {tag}_b y on x.j = y.i group by 1), "
        f"{tag}_c as (select i, count(*) nc from (select x.i i, y.j j from {a} x join {b} y on x.j = y.i group by 1, 2) group by 1), "
        f"{tag}_r as (select w.i, work, na, nc from {tag}_w w join {tag}_c c on w.i = c.i)"
    )
