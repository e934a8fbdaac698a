"""Evaluation integrity on Spark: boundary audits, answer rewards, judging statistics."""
