"""Token, window, kernel, grouping and backend operators."""
