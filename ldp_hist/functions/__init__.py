"""Column functions: hashes, transforms, randomisers, encodings and codes."""
