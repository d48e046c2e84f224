"""Text functions and functions registered for SQL users."""
