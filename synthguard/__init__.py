"""Release of synthetic records under plausible deniability, as Spark plans."""
