"""Column functions: reproducible draws, vector arithmetic, dyadic test weights."""
