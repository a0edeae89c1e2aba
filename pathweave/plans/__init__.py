"""From a query to a way to run it."""
