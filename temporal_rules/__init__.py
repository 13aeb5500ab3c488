"""Rule programs over facts that hold during time intervals, lowered to Spark DataFrames."""
