"""PySpark-native engine for lossless bidirectional factorization of large text collections."""
