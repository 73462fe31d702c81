"""Spark-native minimum spanning forests, components and their surroundings."""
