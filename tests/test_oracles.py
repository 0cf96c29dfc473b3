import pytest

from tests.harness import compare
from textimpute.plans.oracles import ORACLES
from textimpute.plans.queries import QUERIES

#: Run by the driver at the larger size; here one of each kind.
SOME = ["split_missing", "mask_mnar", "mask_candidates", "assumption_profile", "group_sample_full", "group_sample_shortfall", "nation_patterns", "nation_dependency", "nation_key_dependency",
        "region_dependency", "phone_frequent_native", "phone_maximal", "geo_dependency_sampled", "geo_selection", "conversation_role_selection", "wide_orders_selection", "mobile_selection", "lcs_lengths", "lcs_strings", "topk_diverse_k3", "topk_indexed_k3", "topk_null_cells",
        "topk_random", "topk_embedding", "prompts_k3", "prompt_cost", "impute_nearest_vote", "neighbour_object_sim", "probabilistic_repair", "rouge1", "stream_session_counts"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, name):
    assert compare(spark, sf, QUERIES[name], ORACLES[name]) == ""


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)
