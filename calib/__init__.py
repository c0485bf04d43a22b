"""Calibration of linear models by gradient descent, as many-SUM aggregate queries on Spark."""
