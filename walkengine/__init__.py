"""A Spark-native engine for minimal matching walks over labelled graphs, with operators for training data beside it."""

from pyspark import cloudpickle as _cloudpickle

# Functions of this package travel to executors by value, so a cluster needs no installed copy of it.
import walkengine as _self

_cloudpickle.register_pickle_by_value(_self)
