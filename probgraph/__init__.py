"""Spark-native clustering and reliability queries on graphs whose edges exist with known probability."""
