"""Spark-native all-k-nearest-neighbour search and classification over a grid."""
