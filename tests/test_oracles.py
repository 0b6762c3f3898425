"""Every SQL text of the library ends soon, with one thread, little memory and no optimizer."""

import threading
import time

import duckdb
import pytest

SF = "/root/testdata/sf0.01"
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@pytest.mark.parametrize("begins", ["bgp_W", "bgp_Y", "cap_", "upd_", "stats_", "comm_", "khop_r", "engine_", "x", "agg_", "join_", "sparql_"])
def test_oracles_end(begins):
    from triplefed.queries import all_queries

    found = {n: s for n, s in all_queries()[1].items() if n.startswith(begins)}
    assert found
    for name, sql in found.items():
        c = duckdb.connect()
        c.execute("SET threads = 1; SET memory_limit = '1GB'; PRAGMA disable_optimizer")
        for t in TABLES:
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
        stop = threading.Timer(15, c.interrupt)
        stop.start()
        began = time.time()
        try:
            c.execute(sql).fetchall()
        finally:
            stop.cancel()
        assert time.time() - began < 15, name
