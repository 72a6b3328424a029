"""A Spark-native engine that builds and scores a continuously updated claim-verification benchmark."""
