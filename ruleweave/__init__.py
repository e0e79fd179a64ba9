"""ruleweave: recursive rule programs and training-data operators on Spark DataFrames."""
