"""benchvary: benchmark variation and contamination measurement on Spark DataFrames."""
