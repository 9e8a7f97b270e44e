"""Path skylines of multi-criteria networks on Spark."""
