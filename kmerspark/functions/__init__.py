"""Column functions and Arrow kernels on words over A, C, G, T."""
