import pytest

from sortbit import catalogue

SAMPLE = ["size_p_gen_shuffle", "size_p_frequent_desc", "size_p_rare_asc", "size_k2_p_gen_desc", "size_gray_k2_p_gen_desc", "size_lexgray_k2_p_near_unique_desc", "size_flag31_p_gen_desc", "size_blocks5_p_gen",
          "hamming_p_gen_desc", "runs_p_gen_shuffle", "bitmap_factor_p_dominant_desc", "profile_lineitem", "codes_alpha_k4", "codes_gray_k3", "payload_marker32_p_gen", "where_and_k2", "where_xnor_k1", "eq_partkey_12_k1",
          "group_count_returnflag", "join_index_region", "bin_price", "hierarchy_nation", "flat_nation", "stream_blocks_events",
          "code_lengths", "example_nine_rows_gray", "rollup_nation", "hierarchy_customers", "group_count_where_range_k1", "range_orderkey_equality_k3", "stream_appended_events", "aggregate_functions",
          "density_k2", "payload_runlength_p_gen", "size_p_ten_real_desc",
          "example_seven_facts", "example_six_codes", "example_gray_codes", "example_nine_rows_lex", "code_table", "external_sort_plans"]
ON_TABLES = ["example_seven_facts", "example_six_codes", "example_gray_codes", "example_nine_rows_lex", "example_nine_rows_gray", "code_table", "code_lengths", "external_sort_plans"]


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_its_sql(same, name):
    same(name, catalogue.queries()[name], catalogue.oracle_sql()[name])


def test_every_oracle_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())


@pytest.mark.parametrize("name", ON_TABLES)
def test_sql_asks_a_given_table(name):
    sql = catalogue.oracle_sql()[name]
    assert "FROM lineitem" in sql or "FROM orders" in sql
