"""Objects, queries and tables that the operators read."""
