"""Column functions: geometry, correlation, periods and space-filling codes."""
