"""Analytics over virtual columns on Spark: attributes that a phrase describes and a budget of model calls fills in."""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
