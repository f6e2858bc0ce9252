"""walkfold: declarative path reductions over graphs, run as Spark supersteps."""
