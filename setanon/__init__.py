"""Privacy-preserving release of item sets on Spark."""
