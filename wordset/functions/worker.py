"""Arrow kernels by name, so that executors import the package instead of unpickling it."""

from __future__ import annotations

from collections.abc import Callable
from pathlib import Path

_ROOT = str(Path(__file__).resolve().parents[2])


def on_worker(module: str, name: str, *args) -> Callable:
    """A function for ``mapInArrow`` that calls ``module.name(batches, *args)`` on the executor.

    The kernel is looked up by name, so its module-level caches live as long as the Python worker does.
    Where the package isn't installed on the executors, the driver's own path is tried (local mode).
    """
    root = _ROOT

    def run(batches):
        import importlib
        import sys

        try:
            m = importlib.import_module(module)
        except ImportError:
            sys.path.append(root)
            m = importlib.import_module(module)
        yield from getattr(m, name)(batches, *args)

    return run


def column_kernel(module: str, name: str, schema: str, *args):
    """A column function: ``module.name(array, *args)`` over Arrow arrays, looked up on the executor as above."""
    import pyarrow as pa
    from pyspark.sql import functions as F

    root = _ROOT

    def run(values):
        import importlib
        import sys

        try:
            m = importlib.import_module(module)
        except ImportError:
            sys.path.append(root)
            m = importlib.import_module(module)
        return getattr(m, name)(values, *args)

    run.__annotations__ = {"values": pa.Array, "return": pa.Array}  # types, not their names: they tell the kind of function
    return F.arrow_udf(run, schema)
