"""Selection sketches for join-size estimation on Spark."""

import os
import sys

from pyspark import cloudpickle

# matrices here are small, and threads of their own would fight Spark's tasks for the cores
os.environ.setdefault("OMP_NUM_THREADS", "1")

# Functions that run on executors travel with the job, so nothing has to be installed there.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
