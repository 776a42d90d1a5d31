"""Data-skipping sketches for Spark: capture, use, and incremental maintenance under updates."""
