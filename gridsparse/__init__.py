"""gridsparse: sparse matrices and graphs as distributed tables.

A matrix is a DataFrame of (i, j, v); products over semirings, sub-matrix
extraction and assignment, contraction and graph search are plans over it.
"""

from gridsparse.matrix import SparseMatrix
from gridsparse.semiring import Semiring

__all__ = ["Semiring", "SparseMatrix"]
