"""Spark-native local clustering on attributed graphs, and a training-data toolbox in ``llm``."""
