"""Queries over all rows: bumps of every supplier, paths from every vertex of the line."""

import math

from fieldseg.plans import queries
from fieldseg.sources import fields, synthetic


def test_bumps_of_every_supplier(spark, sf, tmp_path):
    s = fields.table(spark, sf, "supplier")
    # more than ten, some in one place
    many = s.unionByName(s.selectExpr("s_suppkey + 1000 as s_suppkey", *(f"`{c}`" for c in s.columns if c != "s_suppkey")).select(s.columns))
    many.write.parquet(str(tmp_path / "supplier.parquet"))
    dims = (5, 4, 3)
    got = {r.id: r.f for r in synthetic.bump_grid(spark, str(tmp_path), dims, width=1.5).df.collect()}
    at = many.selectExpr(*(f"pmod(xxhash64({7 + i}, s_suppkey), {n}) as c{i}" for i, n in enumerate(dims)), "abs(s_acctbal) as h").collect()
    assert len(at) > 10 and len(got) == 60
    for i, f in got.items():
        v = (i % 5, i // 5 % 4, i // 20)
        want = sum(float(c.h) * math.exp(-sum((v[k] - c[k]) ** 2 for k in range(3)) / 4.5) for c in at)
        assert abs(f - want * synthetic.SCALE) <= 1


def test_paths_from_every_vertex(spark, sf):
    n = fields.FIELDS["line"](spark, sf).df.count()
    assert queries.build()["trace_paths_line"](spark, sf).select("seed").distinct().count() == n
