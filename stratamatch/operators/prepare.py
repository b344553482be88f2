"""Offline preparation: cuboids, strata and factored rows on disk, and fast answers for sub-populations.

A prepared folder holds versions; each has a manifest, written last. A version has

* ``base``: cells of every covariate of any treatment, for all rows — the only pass over the rows
  that counts anything, and what a refresh adds to;
* ``group-i``: cells of each group of correlated treatments, rolled up from the smallest cuboid that
  has their covariates;
* ``strata-t``: the strata of each treatment with both arms, from its group's cells;
* ``rows-i`` and ``rest-i``: the rows of each group whose supergroup (equal shared covariates) has
  both arms of one of its treatments, and the others, which later rows may complete.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import TreatmentSet, UnitSpec
from .effects import stratified_effect
from .lattice import Lattice, base_cuboid, roll_up, strata_of
from .multi import factored_summary, partition_treatments, phi_values, supergroups
from .strata import attach, cem, overlapping, summarize


def prepare(df: DataFrame, treatments: TreatmentSet, path: str, mode: str = "factored") -> dict:
    """Write version 1 under ``path`` (``factored``), or the matched rows of each treatment
    (``matched``). Returns the manifest. Action."""
    names = sorted(treatments.covariates)
    manifest = {"mode": mode, "id": treatments.id, "covariates": {k: list(v) for k, v in treatments.covariates.items()}, "outcomes": list(treatments.outcomes), "groups": [], "version": 1}
    if mode == "matched":
        for t in names:
            cem(df, treatments.spec(t)).write.mode("overwrite").parquet(f"{path}/matched-{t}")
    elif mode == "factored":
        for group, score in partition_treatments(phi_values(df, names), treatments):
            manifest["groups"].append({"treatments": list(group), "score": score, "dims": _dims(treatments, group)})
        _write(df.sparkSession, base_cuboid(df, _dims(treatments, names), treatments.id, names, treatments.outcomes), [df] * len(manifest["groups"]), manifest, path)
    else:
        raise ValueError(mode)
    _save_manifest(df.sparkSession, path, manifest)
    return manifest


def refresh(spark: SparkSession, path: str, delta: DataFrame) -> dict:
    """The next version after appending the rows ``delta``: cells are additive, so only these are
    counted; rows of supergroups that they complete move from ``rest`` to ``rows``. Returns the manifest. Action."""
    manifest = load_manifest(spark, path)
    treatments, old = _treatments(manifest), f"{path}/v{manifest['version']}"
    names = sorted(treatments.covariates)
    dims = _dims(treatments, names)
    base = refreshed(spark.read.parquet(f"{old}/base"), delta, dims, treatments.id, names, treatments.outcomes)
    stored = [[spark.read.parquet(f"{old}/{kind}-{i}").drop("supersubclass") for kind in ("rows", "rest")] for i in range(len(manifest["groups"]))]
    manifest["version"] += 1
    _write(spark, base, [kept.unionByName(rest).unionByName(delta) for kept, rest in stored], manifest, path)
    _save_manifest(spark, path, manifest)
    return manifest


def refreshed(cells: DataFrame, delta: DataFrame, dims, id_column: str, treatments, outcomes=()) -> DataFrame:
    """Cells after appending rows."""
    return roll_up(cells.unionByName(base_cuboid(delta, dims, id_column, treatments, outcomes)), dims, dims)


def _dims(treatments, names):
    return list(dict.fromkeys(c for t in names for c in treatments.covariates[t]))


def _write(spark, base, rows, manifest, path):
    treatments, folder = _treatments(manifest), f"{path}/v{manifest['version']}"
    names = sorted(treatments.covariates)

    def keep(df, name):
        df.write.mode("overwrite").parquet(f"{folder}/{name}")
        return spark.read.parquet(f"{folder}/{name}")

    dims = _dims(treatments, names)
    titles = iter(["base", *(f"group-{i}" for i in range(len(rows)))])
    lattice = Lattice(base, dims, lambda df: keep(df, next(titles)))
    for i, group in enumerate(manifest["groups"]):
        own = group["treatments"]
        cells = lattice.cuboid(group["dims"])
        for t in own:
            keys = list(treatments.covariates[t])
            keep(strata_of(roll_up(cells, keys, group["dims"]), t, keys, treatments.outcomes), f"strata-{t}")
        if len(own) == 1:
            keep(rows[i].withColumn("supersubclass", F.col(treatments.id)), f"rows-{i}")
            keep(rows[i].limit(0), f"rest-{i}")
            continue
        shared = treatments.shared(own)
        whole = keep(roll_up(cells, list(shared), group["dims"]).withColumn("both", supergroups(own)), f"supergroups-{i}")
        keep(attach(rows[i], whole.where("both"), shared, {"max_id": "supersubclass"}), f"rows-{i}")
        keep(attach(rows[i], whole.where("not both"), shared, {}), f"rest-{i}")


def _save_manifest(spark, path, manifest):
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest-{manifest['version']}")


def load_manifest(spark: SparkSession, path: str) -> dict:
    """The manifest of the last version whose write has committed."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    files = hadoop(path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    names = [f.getPath().getName() for f in files.listStatus(hadoop(path))]
    done = [int(n.removeprefix("manifest-")) for n in names if n.startswith("manifest-") and files.exists(hadoop(f"{path}/{n}/_SUCCESS"))]
    return json.loads(spark.read.text(f"{path}/manifest-{max(done)}").first()[0])


def _treatments(manifest):
    return TreatmentSet(manifest["id"], {k: tuple(v) for k, v in manifest["covariates"].items()}, tuple(manifest["outcomes"]))


def predicate_columns(df: DataFrame, where: str) -> set[str]:
    """The columns of ``df`` that a predicate reads, from its analysed plan."""
    found = df.where(where)._jdf.queryExecution().analyzed().condition().references().iterator()
    out = set()
    while found.hasNext():
        out.add(found.next().name())
    return out


def answer(spark: SparkSession, path: str, treatment: str, where: str | None = None, manifest: dict | None = None) -> DataFrame:
    """Effect of a treatment on the sub-population ``where``. If the predicate reads covariates of the
    treatment only, it filters the treatment's strata; else factored rows are filtered and grouped
    again (neither strata nor matched rows may be filtered then: overlap can break)."""
    manifest = manifest or load_manifest(spark, path)
    treatments, folder = _treatments(manifest), f"{path}/v{manifest['version']}"
    i, group = next((i, g) for i, g in enumerate(manifest["groups"]) if treatment in g["treatments"])
    keys = treatments.covariates[treatment]
    strata = spark.read.parquet(f"{folder}/strata-{treatment}")
    if where:
        rows = spark.read.parquet(f"{folder}/rows-{i}")
        if predicate_columns(rows, where) <= set(keys):
            strata = strata.where(where)
        elif len(group["treatments"]) > 1:
            strata = factored_summary(rows.where(where), treatments, tuple(group["treatments"]), treatment)
        else:
            strata = overlapping(summarize(rows.where(where), UnitSpec(treatments.id, treatment, keys, treatments.outcomes)))
    return stratified_effect(strata, treatments.outcomes)


def answers(spark: SparkSession, path: str, names, where: str | None = None) -> DataFrame:
    """``answer`` for several treatments, one row each, with the column ``treatment``."""
    manifest = load_manifest(spark, path)
    parts = [answer(spark, path, t, where, manifest).select(F.lit(t).alias("treatment"), "*") for t in names]
    return reduce(DataFrame.unionByName, parts)


def answer_online(df: DataFrame, treatments: TreatmentSet, treatment: str, where: str | None = None) -> DataFrame:
    """Baseline: the same from unprepared rows."""
    return stratified_effect(overlapping(summarize(df.where(where) if where else df, treatments.spec(treatment))), treatments.outcomes)
