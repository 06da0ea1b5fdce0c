"""Column functions: reproducible noise, marks, randomized response, measures."""
