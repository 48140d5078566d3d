"""Learning on dynamic graphs given as snapshot sequences, with Spark DataFrames."""
