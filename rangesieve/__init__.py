"""rangesieve: approximate range emptiness filters, their baselines and measures, as Spark DataFrames."""
