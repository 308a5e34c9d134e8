"""Vector-leaf, layer-wise gradient boosting on Spark."""
