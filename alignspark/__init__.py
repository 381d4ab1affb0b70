"""alignspark: constraint-based alignment of gappy multivariate series on Spark."""
