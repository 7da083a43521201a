"""Publishing frequent itemsets under differential privacy, on Spark DataFrames."""
