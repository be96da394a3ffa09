"""Spark-native engine that thins finite automata with default transitions."""
