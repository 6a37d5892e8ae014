"""Redundancy scoring of documents on Spark.

``operators.spectrum`` counts n-grams inside each document and keeps only how many
distinct ones occur how often; everything else works on those small spectra.
"""

from pyspark import cloudpickle

import sys

# Kernels travel to the workers by value, so executors need no copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
