"""The mining method, its measures and the baselines, as operators on DataFrames."""
