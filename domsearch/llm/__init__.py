"""Training-data operators.  Nothing else in the library imports this subpackage."""

from pyspark import cloudpickle

# Executors get the functions themselves, so they need no copy of this repository.
cloudpickle.register_pickle_by_value(__import__(__name__, fromlist=["_"]))
