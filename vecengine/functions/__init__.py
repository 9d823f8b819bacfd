"""Column expressions: vectors, quantizers, packing, footprints."""
