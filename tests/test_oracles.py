"""Queries of the library against DuckDB on the smallest tables; the driver compares all at sf0.01."""

import pytest

from sigres.plans import catalog

CHOSEN = [
    "m01_exact_dedup", "m01_members", "m02_words", "m02_qgrams", "m03_subrecord_gap", "m04_all_subrecords", "m05_rel_distance", "m07_closure",
    "m09_histogram", "m10_mixture_vs_poisson", "m12_posterior_ab", "m17_kmax", "m18_index", "m20_eliminate_gapped", "m20_eliminate_contiguous",
    "m22_product", "m24_verified_jaro_winkler", "m24_verified_rules", "m27_forest", "m29_components_shuffled", "m30_resolve_documents",
    "m34_incremental", "f05_compose", "f07_random", "f09_fallback", "b01_all_pairs", "b02_key_blocking", "b14_minlabel", "m16_tune",
    "a01_pair_quality", "a15_cluster_quality", "w01_bibliography_pages", "w05_people", "w06_mentions_closure", "w08_street_world",
    "rel_asof_join", "rel_range_join", "io_csv", "st_s06_stateful_counts", "udaf_noisy_or",
]


@pytest.mark.parametrize("name", CHOSEN)
def test_agrees_with_oracle(name, agrees):
    agrees(catalog.queries()[name], catalog.oracles()[name])


def test_names():
    assert set(catalog.oracles()) <= set(catalog.queries())
