"""Column functions: token budgets, hashing buckets, prompts and output schemas."""
