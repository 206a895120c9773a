"""Queries against their SQL on the smallest tables."""

import pytest
from oracle import database, differ

import __spark_entry__ as entry

FOLDER = "/root/testdata/sf0.001"
#: A spread over all parts; tests/oracle.py runs every query.
NAMES = "prep_audit vocab_ids packed_roundtrip length_groups theta_prob phi_prob joint_ll bucket_masses snapshot_sweep word_shards_weighted word_shards_snake schedule_conflicts phi_delta_merge alpha_step r_best topic_l1_smoothed topic_pairs_below topic_clusters word_likelihood wand_topk map_score auc topic_pmi perplexity word_triples_frequent join_asof_click stream_session_users stream_dedupe".split()


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, name):
    assert differ(entry.queries()[name](spark, FOLDER), database(FOLDER), entry.oracle_sql()[name]) is None


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    top = entry.entry(spark, iterations=1).collect()
    assert {r.topic for r in top} <= set(range(8)) and max(r["rank"] for r in top) == 10
