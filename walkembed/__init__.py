"""Information-driven random-walk embedding, and the relational operators around it, on Spark DataFrames."""
