"""Spark-native engine for table-centred corpora: text curation, table cleaning,
encoding, sample generation, retrieval and scoring as DataFrame plans."""

import sys

from pyspark import cloudpickle

# Python workers may start in another folder, so functions of this package travel by value.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
