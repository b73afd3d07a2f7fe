"""hypernear: hyperplane nearest-neighbour analytics, native to Spark.

Functions of this package that run on executors are pickled by value, so a
cluster needs no copy of the package on its workers.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
