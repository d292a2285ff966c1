"""Extremal eigenpairs of large self-adjoint operators on Spark DataFrames."""
