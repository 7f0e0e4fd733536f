"""Learn and run DNF blocking schemes over heterogeneous datasets on Spark."""

__version__ = "0.1.0"
