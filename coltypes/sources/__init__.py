"""Tables, collections of tables, and where results go."""
