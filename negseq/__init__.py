"""Sequential patterns with absences on Spark, and the plans around them.

Functions of this package that run inside Python workers are pickled by value, so
executors need no copy of the repository on their import path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
