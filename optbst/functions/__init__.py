"""Part of the search-tree engine."""
