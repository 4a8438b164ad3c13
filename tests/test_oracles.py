import pytest

from conflate.queries import places, relational
from tests.helpers import plain

#: The methods' own queries that are quick on the smallest tables, and every relational one.
METHODS = """box_filter sphere_filter theme_filter grid_cells grid_in_area poi_in_area adaptive_leaves adaptive_leaves_by_level fixed_grid_loss capped_pages procurement_cost
procurement_cost_fixed dedup_uid address_norm address_parse address_render standardised geojson_roundtrip page_fields pairs_100m pairs_unordered tile_pairs pairs_brute knn_pairs radius_sweep
name_sim name_sim_lev_sum name_sim_unsorted addr_tf addr_idf_local addr_tfidf addr_tfidf_smooth addr_tfidf_neigh addr_tfidf_global addr_tfidf_cell pair_features tile_kernel wsa_published m1_wsa m2_wsa m3_wsa wsa_grid
wsa_best labelled_counts class_weights oversample undersample balanced_sets cv_folds matches_undirected components star_clusters mutual_best unified unify_bounds coverage overlap cluster_quality
type_components ngram_vectors taxonomy_map taxonomy_unmapped taxonomy_custom taxonomy_exact term_vectors verify_reasons verify_resolved validation_report accessibility pipeline_wsa""".split()


def check(spark, duck, sf_dir, f, sql):
    got, want = f(spark, sf_dir).toPandas(), duck.execute(sql).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert plain(got) == plain(want)


@pytest.mark.parametrize("name", METHODS)
def test_method(spark, duck, sf_dir, name):
    check(spark, duck, sf_dir, places.QUERIES[name], places.ORACLES[name])


@pytest.mark.parametrize("name", list(relational.ORACLES))
def test_relational(spark, duck, sf_dir, name):
    check(spark, duck, sf_dir, relational.QUERIES[name], relational.ORACLES[name])


def test_entry_has_rows(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 100
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
