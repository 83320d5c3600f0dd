"""View builders, search, navigation, maintenance and measures on DataFrames."""
