"""Metrics, NumPy kernels and matching: everything that runs inside a task or on the driver without Spark."""
