"""Column functions: dissimilarities, text folding, hashing."""
