"""Training-data operators. Nothing outside this subpackage imports it."""

import os

# small matrices: more BLAS threads than one only wait for each other (without effect once numpy is loaded)
os.environ.setdefault("OMP_NUM_THREADS", "1")
