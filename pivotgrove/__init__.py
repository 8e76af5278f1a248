"""Spark-native multi-way spatial index engine: build, insert, search, choose a strategy, measure."""
