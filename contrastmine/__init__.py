"""Contrast-pattern mining over positive and negative literals, native to Spark."""

from pyspark import cloudpickle as _cloudpickle
import sys as _sys

# Executors need no copy of the package on their path: its functions travel with the task.
_cloudpickle.register_pickle_by_value(_sys.modules[__name__])
