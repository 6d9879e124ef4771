"""Operators for preparing language-model training data. Nothing outside this folder imports it."""

import sys

from pyspark import cloudpickle

# Python workers get this folder's functions with the task, so executors need no copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
