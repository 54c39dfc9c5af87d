"""proxgraph: random-walk node proximity with error bounds, on Spark DataFrames."""
