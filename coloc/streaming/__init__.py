"""The methods over streams."""
