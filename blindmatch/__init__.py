"""Multi-party masked record linkage on Spark, with corpus operators in ``blindmatch.llm``."""

import sys

from pyspark import cloudpickle

# Task functions travel by value, so executors need no installed copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
