"""Top-k functional dependencies by redundancy, and the operators around them, as Spark plans."""
