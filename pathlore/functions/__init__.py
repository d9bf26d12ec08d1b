"""User-defined functions: path expressions as table functions, and run search a component in Python."""
