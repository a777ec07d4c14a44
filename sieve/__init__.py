"""Spark-native static membership filters: build, probe, gate, measure."""
