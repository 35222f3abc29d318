"""Spark-native search for statistically significant intervals in very many time series."""
