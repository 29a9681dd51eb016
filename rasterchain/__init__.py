"""Spark-native chains of elementary minimum/maximum filters on rasters."""
