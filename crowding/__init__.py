"""Spark-native engine for k-crowded graphs: lifting, realization, measures and the operators around them."""
