"""Searches that run to the end, against a plain one."""

from rowproduct import catalog
from rowproduct.catalog.studies import SOURCES
from rowproduct.sources.builders import part_follow


def plain(edges, source):
    level, paths, order, at = {source: 0}, {source: 1}, [source], [source]
    while at:
        new = {}
        for v in at:
            for w in edges.get(v, ()):
                if w not in level:
                    new[w] = new.get(w, 0) + paths[v]
        level |= dict.fromkeys(new, level[at[0]] + 1)
        paths |= new
        at = list(new)
        order += at
    dep = dict.fromkeys(order, 0.0)
    for v in reversed(order):
        dep[v] = sum(paths[v] / paths[w] * (1 + dep[w]) for w in edges.get(v, ()) if level[w] == level[v] + 1)
    return level, paths, {v: d for v, d in dep.items() if v != source}


def test_searches_run_to_the_end(spark, sf, monkeypatch):
    from rowproduct.catalog import studies

    m = part_follow(spark, sf)
    near = m.with_df(m.df.where("abs(i - j) < 12").select("i", "j", "v"))  # so thin that searches go deep
    edges = {}
    for r in near.df.collect():
        edges.setdefault(r.i, []).append(r.j)
    monkeypatch.setattr(studies, "PF", lambda s, d: near)
    want = [plain(edges, s) for s in SOURCES]
    assert max(max(x[0].values()) for x in want) > 3
    rows = catalog.QUERIES["bc_paths"](spark, sf).collect()
    assert {(r.search, r.vertex): (r.level, r.paths) for r in rows} == {(k, v): (lv[v], p[v]) for k, (lv, p, _) in enumerate(want) for v in lv}
    rows = catalog.QUERIES["msbfs_levels"](spark, sf).collect()
    assert {(r.search, r.vertex): r.level for r in rows} == {(k, v): x for k, (lv, _, _) in enumerate(want) for v, x in lv.items()}
    score = {}
    for _, _, dep in want:
        for v, x in dep.items():
            score[v] = score.get(v, 0.0) + x
    got = {r.vertex: r.score for r in catalog.QUERIES["bc_scores"](spark, sf).collect()}
    assert set(got) == set(score) and all(abs(got[v] - score[v]) < 1e-6 * max(1, abs(score[v])) for v in got)
