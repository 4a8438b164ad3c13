"""Column functions and SQL registrations."""
