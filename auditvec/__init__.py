"""auditvec: auditable nearest-neighbour retrieval on Spark DataFrames."""

import os
import sys
from pathlib import Path


def _ship_by_value() -> None:
    """Where Python workers could not import this package, send its functions with the task instead."""
    root = str(Path(__file__).resolve().parents[1])
    seen = [os.getcwd(), *os.environ.get("PYTHONPATH", "").split(os.pathsep)]
    if root not in {os.path.realpath(p) for p in seen if p}:
        from pyspark import cloudpickle

        cloudpickle.register_pickle_by_value(sys.modules[__name__])


_ship_by_value()
