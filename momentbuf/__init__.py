"""Range aggregates over very large indexed arrays from small precomputed buffers, on Spark."""
