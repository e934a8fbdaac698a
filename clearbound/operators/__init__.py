"""Methods on DataFrames: audit, grading, judging, statistics, corpus."""
