"""claimfold: resolve many conflicting records of one entity into one, on Spark."""
