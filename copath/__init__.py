"""Rules between path patterns of one large property graph, as Spark DataFrame plans."""

import sys

from pyspark import cloudpickle

#: Functions of this package travel to the executors by value, so a cluster needs
#: no copy of it on the workers' own Python path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
