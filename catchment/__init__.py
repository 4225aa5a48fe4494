"""Reverse-nearest-neighbour influence maps as lazy Spark plans.

Kernels of this package travel to executors by value, so a cluster needs no
copy of the repository on its workers' Python path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
