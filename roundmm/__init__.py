"""roundmm: semiring matrix products in a tunable number of shuffle rounds, on Spark DataFrames."""
