"""Signed-bucket sketches, tree reductions and compressed training as Spark plans."""

from pyspark import cloudpickle as _cloudpickle
import sys as _sys

# Functions of this package travel to the executors by value: a cluster needs
# no copy of the package on its workers.
_cloudpickle.register_pickle_by_value(_sys.modules[__name__])

__version__ = "0.1.0"
