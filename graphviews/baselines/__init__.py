"""Related maintenance techniques, each able to do what the literature says and no more."""
