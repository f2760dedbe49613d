"""Link-importance scores kept fresh on changing graphs, on Spark DataFrames."""
