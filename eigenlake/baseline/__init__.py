"""Direct and iterative solvers to compare with."""
