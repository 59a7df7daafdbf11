"""Tables, edge lists, graphs over the given tables, features and labels."""
