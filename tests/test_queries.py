"""Every registered check against its SQL at sf0.001."""

import pytest
from .compare import assert_same, connection
from .conftest import DATA

from chunkgraph.workloads.queries import oracle_sql, queries

# the slow ones run at sf0.01 in the driver; here one of each kind
SLOW = {"bfs_cs", "bfs_op", "bfs_cp", "bfs_noflat_ps", "bfs_plain_ps", "bfs_b256_ps", "b5_static_sparse_bfs_ps", "b1_bfs_ps", "local_cluster_op", "chunk_stats_sweep", "graph_stats", "bc_ps", "mis_op", "stream_90_10_final_graph", "as_of_graph"}
SLOW |= {f"bfs_{ids}_ids_{mode}" for ids in ("negative", "large") for mode in ("sparse", "auto")} | {"bc_sparse_ps", "bc_flat_ps", "b1_bc_ps", "b2_bc_ps", "b4_bc_ps", "b2_bfs_ps", "codec_delta_bfs_ps", "mis_coded_web", "local_cluster_web"}


@pytest.fixture(scope="module")
def duck():
    return connection(DATA)


@pytest.mark.parametrize("name", sorted(set(queries()) - SLOW))
def test_query(spark, duck, name):
    df = queries()[name](spark, DATA)
    if name in oracle_sql():
        assert_same(df, duck, oracle_sql()[name])
    else:
        assert df.count() > 0


def test_entry_point(spark):
    import __spark_entry__

    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert __spark_entry__.entry(spark).count() > 0


@pytest.mark.parametrize("name", ["data_source_rmat", "memory_paper_graphs", "rmat_edges", "udtf_rmat", "string_tokens"])
def test_query_reads_a_given_table(spark, name):
    assert any(f.startswith("file:") and DATA in f for f in queries()[name](spark, DATA).inputFiles())
