"""Linear operators of temporal graphs, as joins; nothing dense is ever formed."""

from .base import LinearOperator, random_block, spmv
from .laplacian import DeformedLaplacian, Laplacian, choose_r
from .modularity import ModularityOp, MultisliceModularityOp
from .nonbacktracking import NonBacktracking, estimate_affinity, estimate_eta

__all__ = ["DeformedLaplacian", "Laplacian", "LinearOperator", "ModularityOp", "MultisliceModularityOp", "NonBacktracking", "choose_r", "estimate_affinity", "estimate_eta", "random_block", "spmv"]
