"""Dense Tucker decomposition on Spark: planners for tensor-times-matrix work and an engine that runs their plans."""
