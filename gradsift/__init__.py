"""Spark-native sketch-compressed training and large-scale sketch analytics."""
