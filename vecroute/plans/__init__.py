"""Index building and querying as Spark plans."""
