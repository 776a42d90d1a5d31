"""Evaluation of plans over signed, sketch-annotated rows, and their incremental maintenance."""
