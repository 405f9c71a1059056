"""edgemill: scale-free graph generation, relabelling and CSR conversion as Spark plans."""
