"""Operators of a training-data pipeline.  Nothing else in the library imports this subpackage."""

import sys

from pyspark import cloudpickle

# Python workers on a cluster need not have this repository installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
