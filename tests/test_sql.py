"""The SQL surface."""

from __future__ import annotations

from sparsegrid.sql import multiply_views, register, triangles_of_view


def test_views(spark, sf):
    names = register(spark, sf)
    assert "supply" in names and spark.sql("SELECT count(*) AS n FROM handoff").first()["n"] == 207
    spark.sql("SELECT col AS row, row AS col, val FROM supply").createOrReplaceTempView("supply_t")
    out = multiply_views(spark, "supply_t", "supply", into="gram")
    assert out.count() == 100 and spark.sql("SELECT sum(val) AS s FROM gram").first()["s"] == 18_233
    assert triangles_of_view(spark, "handoff", directed=True, into="tri").count() == 871
    assert spark.sql("SELECT count(*) AS n FROM divisor_grid(64)").first()["n"] == 28
