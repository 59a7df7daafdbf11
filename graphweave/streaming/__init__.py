"""Graph operators over arriving edges."""
