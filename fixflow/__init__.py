"""fixflow: recursive, rule-based iterative analytics lowered to Spark DataFrames."""
