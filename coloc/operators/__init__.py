"""The methods' steps."""
