"""A query of each family against its SQL on the smallest tables (the driver runs all of them)."""

import pytest

from seqentropy.plans import relational  # noqa: F401
from seqentropy.plans.queries import REGISTRY

from .oracle import same

NAMES = ["s3_symbol_counts", "s7_corpus_offsets", "b2_b11_block_entropies", "b5_b10_conditional", "p4_match_lengths", "p7_prefix_tree", "p9_decoded_parses", "w5_worked_parses", "c1_suffix_tree_counts", "e4_window_engine", "e5_shortest_gain_incremental_users", "e5_blend_full_users", "e5_min_total_gain_full_users", "a2_final_capital", "a5_convergence", "g1_map_orbits", "g4_g5_automaton", "w17_information_by_letter", "w20_supplier_histories", "w21_windowed_entropy", "r_asof_join", "r_window_functions",
         "b13_assumed_tail", "p1_p3_p8_dictionary_histories", "p2_p3_p8_substring_histories", "c3_c6_tree_statistics_users", "c1_suffix_words", "s6_sign_partition", "s8_counts_after_a_precursor", "e7_given_weights", "e9_tree_mixture", "y3_exact_rates", "x1_tail_fits", "x2_tail_fit_of_known_limit", "w21_online_code_lengths", "v4_scramble_gap_sequences", "w13_truncated_trees", "w15_forecast_table"]


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, sf, name):
    f, sql = REGISTRY[name]
    same(spark, sf, f, sql)


def test_equal_values_go_by_the_id(spark, tmp_path):
    """The first of several least and largest values, in any order of the rows; null values don't count."""
    values = [None, 5.0, 0.0, 0.0, 9.0, 3.0, 9.0, 0.0, 9.0, 4.0]
    rows = [(k, k % 3, "view", v) for k, v in enumerate(values)]
    spark.createDataFrame(rows[::-1], "event_id long, user_id long, event_type string, value double").repartition(4, "event_id").write.parquet(f"{tmp_path}/events.parquet")
    got = REGISTRY["r_aggregates"][0](spark, str(tmp_path)).first()
    assert (got.least, got.most, got.n) == (2, 4, 10)


MOVED = ["a3_ideal_growth", "b7_expected_bias", "c1_suffix_tree_counts", "c1_suffix_words", "g6_y3_chains_with_known_rates", "w5_worked_parses", "x1_tail_fits", "x2_tail_fit_of_known_limit", "y3_exact_rates"]


@pytest.mark.parametrize("name", MOVED)
def test_needs_its_table(spark, tmp_path, name):
    """Queries that once made up their data: without tables they fail."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        REGISTRY[name][0](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("name", [x for x in MOVED if REGISTRY[x][1]])
def test_moved_equals_sql(spark, name):
    f, sql = REGISTRY[name]
    same(spark, "/root/testdata/sf0.01", f, sql)


def test_chains_reach_their_rates(spark):
    got = REGISTRY["g6_y3_chains_with_known_rates"][0](spark, "/root/testdata/sf0.01").collect()
    assert len(got) == 8 and all(-0.03 < r.rel_error < 0.12 for r in got)


def test_worked_examples(spark):
    """Parses, repeat lengths and prefix trees of 110101001111; suffix trees and counts of short sequences."""
    from seqentropy.functions import symbols as S
    from seqentropy.operators import predict as P
    from seqentropy.operators import repeats as R
    from seqentropy.plans.queries import worked

    frame = lambda *texts: spark.createDataFrame(list(enumerate(texts)), "seq_id long, t string")
    assert {r.what: r.answer for r in worked(frame("110101001111")).collect()} == {"dictionary": "1,10,101,0,01,11,1", "substring": "1,10,10100,111,1", "lengths": "1,2,1,5,4,3,2,3,3", "tree4": "0,10100,10101,11", "tree5": "0100,0101,10100,10101,11"}
    words = sorted((r.seq_id, r.k, r.word) for r in R.suffix_words(frame("1010", "10101"), "01101").collect())
    assert [w for *_, w in words] == ["11", "110", "01", "010", "11", "110", "1101", "010", "0101"]
    counts = {(r.ctx, r.sym): r.cnt for r in P.context_counts(S.chunks(frame("11010100"), 2), 2).collect()}
    assert [counts[k] for k in (("1", "0"), ("1", "1"), ("11", "0"), ("", "0"), ("", "1"))] == [3, 1, 1, 4, 4]
