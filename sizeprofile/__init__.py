"""Private group-size profiles on Spark.

For every node of a region tree: how many groups have each size, released under differential privacy for entities, as
non-negative whole numbers that sum to the public number of groups and add up from children to parents.
"""

from pyspark import cloudpickle

import sizeprofile as _self

cloudpickle.register_pickle_by_value(_self)  # executors need no copy of the package
