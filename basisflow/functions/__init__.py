"""Column expressions and Arrow kernels: chunking, packing, codes, fingerprints."""
