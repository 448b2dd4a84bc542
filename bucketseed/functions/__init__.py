"""Column functions: permutations, hash families, distances and feature builders."""
