"""What queries of pairs hold on disk when their pairs begin: written tables, no shuffle."""

import os
import re
import time

import pytest

from stratamatch import workloads
from stratamatch.sources.shared import shared_folder
from stratamatch.sources.units import line_units, scored_units, written_codes

workloads.load()


def shuffles(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ")
    return set(re.findall(r"shuffle_\d+_", files))


def tables(spark):
    return set(os.listdir(shared_folder(spark).removeprefix("file://")))


@pytest.mark.parametrize("query, held", [("nn_candidates", {"scores", "lists"}), ("dist_coarsened", {"coded"}), ("nn_theta_baseline", {"scores", "treated"}), ("udf_distance", {"scores", "lists", "distances"})])
def test_pairs_begin_without_shuffles_and_passing_tables(spark, small, query, held):
    """The shuffles of the joins of units, and the lines they were made from, once stayed beside the pairs."""
    shuffled, written = shuffles(spark), tables(spark)
    pairs = workloads.QUERIES[query](spark, small)
    deadline = time.time() + 10
    while (left := shuffles(spark) - shuffled) and time.time() < deadline:
        time.sleep(0.1)
    assert not left
    assert {name.split("-")[0] for name in tables(spark) - written} == held
    assert pairs.count() > 0


def test_written_codes_are_those_of_all_scored_units(spark, small):
    names = ("uid", "t_bulk", "p_brand", "p_type", "cx_total")
    want = scored_units(line_units(spark, small)).select(*names)
    got = written_codes(spark, small)
    assert got.dtypes == want.dtypes
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
