"""Driver queries: methods and experiments, and the relational operators around them."""
