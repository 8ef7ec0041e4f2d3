"""Tables, graphs of the tables, generators and edge files."""
