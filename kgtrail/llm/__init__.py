"""Training-data operators: tokenising, decontamination, token files, chat views, resharding,
personal data, exact and near duplicates, toxicity.

Nothing outside this subpackage imports it. Code that runs in Python workers is pickled by value,
so executors need PySpark and the numeric libraries but not this repository.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
