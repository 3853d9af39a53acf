"""Expert-steered extraction of structured records from heterogeneous web documents, on Spark DataFrames."""
