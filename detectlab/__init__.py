"""detectlab: Spark-native curation, distillation and evaluation of labelled text corpora.

The package is pickled by value, so Python stages run on executors that have
Spark but not this package installed.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
