"""Shared plumbing: table access, lineage cuts, and columns that only pass through."""

from __future__ import annotations

import functools
import inspect

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from axisgrove.plans.storage import cut, release, shared_folder

__all__ = ["cut", "keeping", "release", "set_aside", "shared_folder", "table"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the parquet tables below ``sf_dir``."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _free(name: str, taken: set[str]) -> str:
    while name.lower() in taken:
        name += "_in"
    return name


def set_aside(df: DataFrame, made: list[str]) -> DataFrame:
    """Columns that have the name of a result, in any case, get ``_in`` added until the name is free."""
    results = {c.lower() for c in made}
    taken = results | {c.lower() for c in df.columns if c.lower() not in results}
    for c in df.columns:
        if c.lower() in results:
            name = _free(c, taken)
            taken.add(name.lower())
            df = df.withColumnRenamed(c, name)
    return df


def keeping(operator):
    """For operators with a frame as first argument and ``keep``, the columns that pass through: those travel under
    names of their own and so clash with nothing inside. One that has the name of a result comes back with ``_in`` added."""
    signature = inspect.signature(operator)
    frame = next(iter(signature.parameters))

    @functools.wraps(operator)
    def run(*args, **kwargs):
        call = signature.bind(*args, **kwargs)
        call.apply_defaults()
        keep = list(call.arguments["keep"])
        inner = [f"__kept{i}" for i in range(len(keep))]
        call.arguments[frame] = call.arguments[frame].withColumns({i: F.col(f"`{c}`") for i, c in zip(inner, keep, strict=True)})
        call.arguments["keep"] = type(call.arguments["keep"])(inner)
        found = operator(*call.args, **call.kwargs)
        results = [c for c in found.columns if c not in inner]
        taken, names = {c.lower() for c in results}, []
        for c in keep:
            names.append(_free(c, taken))
            taken.add(names[-1].lower())
        return found.select(*[F.col(i).alias(n) for i, n in zip(inner, names, strict=True)], *[F.col(f"`{c}`") for c in results])

    return run
