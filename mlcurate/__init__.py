"""Language-adaptive corpus curation on Spark DataFrames."""
