"""elimspark: exact graph width by distributed subset search, on Spark.

Functions of this package travel to the Python workers by value, so the executors of a
session that someone else started need not have it installed.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
