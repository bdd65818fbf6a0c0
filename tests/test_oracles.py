"""Every relational query and the main methods against a second engine on the smallest tables."""

import duckdb
import pytest

from edgefold import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
METHODS = ["pagerank_scaled_10", "pagerank_double_5", "pagerank_message_woken", "sssp_dist", "sssp_weighted_pred", "cc_sharedline", "cc_contract", "scc_strong", "proxy_measures_k4", "place_at_target", "local_ids", "csr_rows", "greedy_assign_trade_mixed", "greedy_oblivious_trade", "message_counts", "degree_profile"]


def plain(value):
    if isinstance(value, float):
        return round(value, 6)
    return int(value) if type(value).__name__ == "Decimal" and value == int(value) else value


@pytest.fixture(scope="module")
def second(small):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", [*METHODS, *(n for n, (_, s) in registry.PAIRS.items() if s)])
def test_same_rows(spark, small, second, name):
    df = registry.queries()[name](spark, small)
    cursor = second.execute(registry.oracle_sql()[name])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == sorted(df.columns)
    order = [names.index(c) for c in df.columns]
    want = sorted((tuple(plain(r[i]) for i in order) for r in cursor.fetchall()), key=repr)
    assert sorted((tuple(map(plain, r)) for r in df.collect()), key=repr) == want
