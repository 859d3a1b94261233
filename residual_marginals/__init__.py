"""Private marginal tables on Spark, by residual decomposition."""
