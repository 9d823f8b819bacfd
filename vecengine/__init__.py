"""Vector search with per-vector scalar quantization, as DataFrame programs."""
