import duckdb
import pytest

from cfengine import queries
from cfengine.operators.metrics import stage_metrics

#: Queries that once made their data up.
NAMES = [
    "cost_projection",
    "exp_E15_E16_machines",
    "planted_source",
    "scaling_table",
    "speedup_table",
    "tile_latency",
]


@pytest.mark.parametrize("name", NAMES)
def test_a_given_table_is_read(spark, sf, name):
    got = []
    read = stage_metrics(spark, lambda: got.extend(map(tuple, queries.QUERIES[name](spark, sf).collect())))
    assert read["input_bytes"] > 3000 and got
    if name in queries.ORACLES:
        c = duckdb.connect()
        for t in ("lineitem", "orders", "events"):
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
        key = lambda r: [str(v) for v in r]
        assert sorted(got, key=key) == sorted(c.execute(queries.ORACLES[name]).fetchall(), key=key)
