"""modelsort: model-driven partition sorting and its neighbours on Spark DataFrames."""
