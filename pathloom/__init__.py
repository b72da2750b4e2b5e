"""pathloom: regular path queries over edge-labelled graphs, as Spark DataFrame plans."""

import sys

from pyspark import cloudpickle

# Functions that run on executors are shipped by value, so a cluster needs no copy of this package on its nodes.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
