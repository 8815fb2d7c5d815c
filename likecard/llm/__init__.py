"""Operators for training-data pipelines.

Nothing else in the library imports this subpackage. Functions that Spark ships
to its Python workers are pickled by value, so executors need none of it
installed.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
