"""Per-vector curve quantization of embedding vectors on Spark."""
