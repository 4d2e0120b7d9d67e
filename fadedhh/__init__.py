"""Time-faded heavy hitters on Spark: forward-decayed weights, mergeable two-counter sketches, queries."""

__version__ = "0.1.0"
