"""A Spark-native engine for curating training data of language models."""
