"""Place queries over geo-tagged term streams, as Spark DataFrames.

Python functions of this package that run on executors are shipped by value, so
executors need PySpark, numpy and pandas but no copy of the package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
