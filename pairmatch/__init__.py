"""Low-label matching of records of any two formats, expressed as Spark plans."""
