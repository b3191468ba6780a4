"""Column functions: ids, vectors, cost curves; and their SQL registrations."""
