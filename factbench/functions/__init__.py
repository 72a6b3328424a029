"""Column functions: built-in expressions only, so that plans stay in code generation."""
