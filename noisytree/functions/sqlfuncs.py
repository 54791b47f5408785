"""Functions for SQL users: box shares, keyed noise, and range counts over a registered tree."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from noisytree.functions.noise import DEFAULT, Noise


def register(spark: SparkSession, noise: Noise = DEFAULT) -> None:
    """box_fraction, laplace_at and cell_id as temporary SQL functions; hilbert_blocks as a table function."""
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION box_fraction(lo DOUBLE, hi DOUBLE, qlo DOUBLE, qhi DOUBLE) RETURNS DOUBLE
        RETURN CASE WHEN hi > lo THEN greatest(0D, least(hi, qhi) - greatest(lo, qlo)) / (hi - lo) WHEN lo >= qlo AND lo < qhi THEN 1D ELSE 0D END""")
    u = f"((CAST(conv(substr(md5(concat_ws(':', '{noise.seed}', k)), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496D)"
    if not noise.secure:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION laplace_at(k STRING, scale DOUBLE) RETURNS DOUBLE RETURN scale * CASE WHEN {u} < 0.5D THEN ln(2 * {u}) ELSE -ln(2 * (1 - {u})) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_id(v DOUBLE, lo DOUBLE, hi DOUBLE, n BIGINT) RETURNS BIGINT RETURN least(n - 1, greatest(0L, CAST(floor((v - lo) / (hi - lo) * n) AS BIGINT)))")

    from pyspark.sql.functions import udtf

    @udtf(returnType="start: bigint, side: int")
    class HilbertBlocks:
        def eval(self, lo: int, hi: int):
            from noisytree.functions.hilbert import blocks

            for start, k in blocks(lo, hi):
                yield start, 1 << k

    spark.udtf.register("hilbert_blocks", HilbertBlocks)


def register_tree(spark: SparkSession, nodes: DataFrame, name: str) -> None:
    """A plane release as view ``name`` (with parents' boxes) and the table function ``name``_count(x0, x1, y0, y1)."""
    nodes.createOrReplaceTempView(name)
    inside = "{0}x0 >= qx0 AND {0}x1 <= qx1 AND {0}y0 >= qy0 AND {0}y1 <= qy1"
    cut = "is_leaf AND x0 < qx1 AND x1 > qx0 AND y0 < qy1 AND y1 > qy0"
    # Rows first, sums after: an aggregate may not mix columns and parameters.
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}_count(qx0 DOUBLE, qx1 DOUBLE, qy0 DOUBLE, qy1 DOUBLE) RETURNS TABLE (estimate DOUBLE)
        RETURN SELECT coalesce(sum(part), 0D) FROM (
          SELECT beta * CASE WHEN {inside.format('')} THEN 1D
            ELSE (least(x1, qx1) - greatest(x0, qx0)) / (x1 - x0) * (least(y1, qy1) - greatest(y0, qy0)) / (y1 - y0) END AS part
          FROM {name} WHERE ({inside.format('')} AND (px0 IS NULL OR NOT ({inside.format('p')}))) OR ({cut} AND NOT ({inside.format('')})))""")
