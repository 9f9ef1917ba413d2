"""Maps, filters and memberships over DataFrames: build, look up, store, report."""
