"""Spark-native progressive cleaning: train convex models while the rows are still being repaired."""
