"""Spark-native curation of web corpora: ingest, rules, model filters, dedup, sampling and audit."""
