"""Approximate set membership on Spark: quotient-style filters, their storage-tiered forms, Bloom baselines, measures."""
