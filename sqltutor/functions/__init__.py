"""Column functions: responses, skeletons, similarity, SQL text."""
