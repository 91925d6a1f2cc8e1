"""Column functions and their SQL registrations."""
