"""Stable grammar compression on Spark: mergeable, content-named grammars of string collections.

Importing the package asks PySpark's pickler to ship this package's functions by value, so executors need no copy of it.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
