"""Sequence-fingerprint search on Spark: token sequences, histogram shortlists, alignment re-ranking, vector quantisation."""

from pyspark import cloudpickle as _cloudpickle

import seqsearch as _self

# Functions travel to the executors with their modules.
_cloudpickle.register_pickle_by_value(_self)
