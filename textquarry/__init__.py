"""textquarry: curation of language-model training text as Spark plans."""
