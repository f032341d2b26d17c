"""A PySpark engine that curates cases, writes rubrics, scores answers and measures the scores."""

import sys

from pyspark import cloudpickle

# Workers get the functions of this package with the job, so that nothing has to be installed on executors.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
