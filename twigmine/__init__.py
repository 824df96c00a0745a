"""Spark-native mining of tree patterns and tree rules in one large directed graph."""

from __future__ import annotations

import sys

from pyspark import cloudpickle

# Functions that run on executors travel by value, so a cluster needs no copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
