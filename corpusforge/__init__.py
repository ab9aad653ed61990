"""corpusforge: a PySpark engine that turns raw multilingual web text into a clean, document-level corpus."""
