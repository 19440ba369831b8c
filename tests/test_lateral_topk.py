"""The lateral top-k of a customer key that several rows share, against its SQL."""

import pyarrow as pa
import pyarrow.parquet as pq
from oracle import TABLES, difference

from __spark_entry__ import oracle_sql, queries


def test_shared_customer_keys(spark, sf, tmp_path):
    for name in TABLES:
        pq.write_table(pq.read_table(f"{sf}/{name}.parquet").slice(0, 200), tmp_path / f"{name}.parquet")
    customers = pq.read_table(f"{sf}/customer.parquet")
    pq.write_table(pa.concat_tables([customers, customers.slice(0, 40), customers.slice(0, 10)]), tmp_path / "customer.parquet")
    pq.write_table(pq.read_table(f"{sf}/orders.parquet"), tmp_path / "orders.parquet")
    assert difference(queries()["join_lateral_topk"](spark, str(tmp_path)), oracle_sql()["join_lateral_topk"], str(tmp_path)) == ""
