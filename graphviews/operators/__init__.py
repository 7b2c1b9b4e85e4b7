"""Plan operators as DataFrames."""
