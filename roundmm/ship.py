"""Sending this package to Python workers that can't import it from where they run."""

from __future__ import annotations

import functools
import os
import tempfile
import zipfile
from collections.abc import Callable

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> None:
    """Add the package's modules to the session's Python files, once a context. Where it is installed on all machines
    this changes nothing but a small file."""
    sc = spark.sparkContext
    here = os.path.dirname(os.path.abspath(__file__))
    if getattr(sc, "_roundmm_shipped", False) or not os.path.isdir(here):
        return
    path = os.path.join(tempfile.mkdtemp(prefix="roundmm-"), "roundmm_modules.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in sorted(os.walk(here)):
            for name in sorted(names):
                if name.endswith(".py"):
                    file = os.path.join(folder, name)
                    z.write(file, os.path.relpath(file, os.path.dirname(here)))
    sc.addPyFile(path)
    sc._roundmm_shipped = True


def shipped(f: Callable) -> Callable:
    """``f(spark, ...)``, with the package sent first."""

    @functools.wraps(f)
    def run(spark: SparkSession, *args):
        ship(spark)
        return f(spark, *args)

    return run
