"""Recall-calibrated matching on Spark: candidates, ranker, reproducible sampling and threshold selection."""

import sys

from pyspark import cloudpickle

# Functions of this package that run in Python workers travel by value, so executors need no installed copy.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
