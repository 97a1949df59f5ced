"""Small fixed-size summaries of data segments whose errors cancel when many are added up."""

import sys

from pyspark import cloudpickle

# Workers get the code with the task, so the package need not be installed on them.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
