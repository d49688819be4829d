"""Tables, generators and files."""
