"""curvetide: sketched second-order optimisation and data preparation on Spark."""
