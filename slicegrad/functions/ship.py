"""Kernels travel to executors inside the task."""

from __future__ import annotations

import sys

from pyspark import cloudpickle


def ship_by_value(name: str) -> None:
    cloudpickle.register_pickle_by_value(sys.modules[name])
