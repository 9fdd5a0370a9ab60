"""The methods that the exact and local ones are compared with."""
