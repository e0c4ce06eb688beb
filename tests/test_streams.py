"""Streams over tables that are folders of files, as large ones are."""

import pytest

from facetsel.streaming import streams as S


@pytest.fixture(scope="module")
def folders(spark, sf_dir, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("folders"))
    for t in ("documents", "labels", "events"):
        spark.read.parquet(f"{sf_dir}/{t}.parquet").repartition(3).write.parquet(f"{out}/{t}.parquet")
    return out


@pytest.mark.parametrize("name", sorted(S.queries()))
def test_folder_gives_what_a_file_gives(spark, sf_dir, folders, name):
    q = S.queries()[name]
    rows = lambda d: sorted(map(str, q(spark, d).collect()))
    assert rows(folders) == rows(sf_dir)
