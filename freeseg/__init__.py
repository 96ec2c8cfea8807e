"""A Spark-native engine for unsupervised segmentation of symbol sequences."""
