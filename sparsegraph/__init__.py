"""Graph and text analytics as sparse linear algebra over Spark DataFrames."""
