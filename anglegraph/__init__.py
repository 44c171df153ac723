"""anglegraph: angle-pruned neighbour graphs and their surroundings as Spark plans.

Kernels run in Python workers; pickling this package by value lets executors run
them without an installed copy of it.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
