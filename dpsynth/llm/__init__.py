"""Operators of a training-data pipeline: formatting, scoring, filtering, deduplication, encoding.

Nothing outside this subpackage imports it.  Worker code is pickled by value, so
executors need the public libraries only and no copy of this package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
