"""Training-data operators: deduplication, filtering, mixing, search, tokenisation and archive formats.

Nothing outside this subpackage imports it. Python kernels are pickled by value, so executors need no copy of the package.
"""

from pyspark import cloudpickle

import sizeprofile.llm as _self

cloudpickle.register_pickle_by_value(_self)
