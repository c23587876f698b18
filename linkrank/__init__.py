"""Ranking of large directed graphs by their links, on Spark DataFrames."""

from pyspark import cloudpickle as _cloudpickle

import linkrank as _self

# Python workers get this package's functions by value, so that a job does not
# depend on the folder or the PYTHONPATH that an executor was started with.
_cloudpickle.register_pickle_by_value(_self)
