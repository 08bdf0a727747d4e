"""Loss-guided selection of training windows from multi-source series, on Spark."""
