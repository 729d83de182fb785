"""Bit-cleared Bloom filters on Spark: build, probe, clear, measure and apply them as DataFrame plans."""
