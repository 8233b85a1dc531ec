"""Range and semi joins lose no row, whatever the matrix' size."""

from rowproduct import catalog
from rowproduct.catalog import matrices


def test_blocks_cover_rows_past_the_old_end(spark, sf, monkeypatch):
    from rowproduct.sources.builders import part_follow

    m = part_follow(spark, sf)
    far = type(m)(m.df.selectExpr("i + 5000 as i", "j", "v"), m.nrows + 5000, m.ncols)
    monkeypatch.setattr(matrices, "PF", lambda s, d: far)
    want = {}
    for r in far.df.collect():
        n, t = want.get(r.i // 64, (0, 0))
        want[r.i // 64] = n + 1, t + r.v
    for name in ("join_nested_buckets", "join_range_blocks"):
        assert {r.b: (r["rows"], r.total) for r in catalog.QUERIES[name](spark, sf).collect()} == want
