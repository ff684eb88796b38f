"""turnwise: dialogue-to-SQL evaluation on Spark DataFrames."""
