"""Part of the eigenloom package."""
