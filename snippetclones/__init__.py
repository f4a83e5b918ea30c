"""Snippet-clone analytics for very large collections of ordered-cell documents, on Spark."""
