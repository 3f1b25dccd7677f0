"""sigres: probabilistic signature linkage and corpus operators as Spark plans."""
