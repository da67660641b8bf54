"""Column functions: vector algebra and portable hashes."""
