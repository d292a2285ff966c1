"""Schemas that travel between modules, and the errors that a caller may meet."""

from __future__ import annotations

COO = "i long, j long, v double"
COO_COMPLEX = "i long, j long, v double, im double"
BLOCK = "bi int, bj int, nr int, nc int, dtype string, data binary"
PANEL = "b int, nr int, k int, dtype string, data binary"
VEC_LONG = "i long, col int, v double"
VEC_LONG_COMPLEX = "i long, col int, v double, im double"
SPECTRUM = "k int, eigenvalue double, residual double, iteration int, locked boolean, matvecs long"
TRACE = (
    "run_id string, iteration int, phase string, seconds double, active int, locked int, matvecs long, sweeps int, "
    "mu_1 double, mu_ne double, b_sup double, max_degree int, degrees array<int>, residuals array<double>"
)
PLAN = "n long, nev int, nex int, r int, c int, rg int, cg int, bytes_host long, bytes_device long, fits boolean"


class OperatorError(ValueError):
    """The input is not a self-adjoint operator."""


class NotSelfAdjoint(OperatorError):
    pass


class DuplicateCoordinate(OperatorError):
    pass


class MissingIndex(OperatorError):
    pass


class NonFinite(OperatorError):
    pass


class SubspaceTooLarge(ValueError):
    """nev + nex exceeds the order of the operator."""


class NotConverged(RuntimeError):
    """Carries what had converged when the iterations ran out."""

    def __init__(self, message: str, result=None):
        super().__init__(message)
        self.result = result


class DoesNotFit(RuntimeError):
    """Carries the plan that showed it."""

    def __init__(self, message: str, plan=None):
        super().__init__(message)
        self.plan = plan
