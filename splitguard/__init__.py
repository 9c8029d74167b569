"""Raster-fingerprint de-duplication and split-leakage audits on Spark."""

import sys

from pyspark import cloudpickle

# Executors need no copy of this package: its functions travel inside the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
