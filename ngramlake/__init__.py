"""ngramlake: soft, order-preserving text search over token corpora, on PySpark."""
