"""Graph, snapshot, sketch and baseline operators on edge DataFrames."""
