"""gridmin: minimisation of differentiable functions on Spark, data and parameters both distributed."""
