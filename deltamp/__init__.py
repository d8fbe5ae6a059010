"""deltamp: incremental graph message passing and corpus preparation on Spark DataFrames."""
