"""Compact set-similarity sketches on Spark: low-bit minwise signatures, their estimators, baselines and measures."""
