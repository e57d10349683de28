"""lossygrad: lossy gradient communication, expressed as Spark DataFrames."""
