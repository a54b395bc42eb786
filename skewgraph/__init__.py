"""Load-balanced, frontier-driven graph analytics on Spark."""
