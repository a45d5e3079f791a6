"""General relational operators around the stages."""
