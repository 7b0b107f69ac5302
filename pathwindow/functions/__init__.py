"""Column builders and small driver-side arithmetic."""
