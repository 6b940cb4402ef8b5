"""Sharing movement data under local differential privacy, on Spark.

Worker-side functions are pickled by value, so executors need the public
libraries only and not this package on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
