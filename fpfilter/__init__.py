"""Approximate set membership at scale: fingerprint filters built, persisted, probed and measured on Spark."""
