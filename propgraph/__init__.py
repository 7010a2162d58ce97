"""Property-graph analytics on Spark DataFrames: one physical layout, a table view and a graph view."""
