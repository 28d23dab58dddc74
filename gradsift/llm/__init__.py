"""Corpus operators for training data. Nothing else in the library imports this.

Functions that run in Python workers are sent by value, so that executors
need no copy of this package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
