"""The cube over buckets has all levels, also where there are no atoms."""

from halograph.catalog import ORACLE_SQL, QUERIES
from oracle import TABLES, check


def test_cube_of_no_atoms_has_its_grand_total(spark, sf_dir, tmp_path):
    for t in TABLES:
        rows = spark.read.parquet(f"{sf_dir}/{t}.parquet")
        (rows.limit(0) if t == "orders" else rows.limit(1)).coalesce(1).write.parquet(f"{tmp_path}/made/{t}")
        (file,) = (tmp_path / "made" / t).glob("*.parquet")
        file.rename(tmp_path / f"{t}.parquet")
    check(spark, str(tmp_path), QUERIES["op_cube"], ORACLE_SQL["op_cube"])
