"""See the package docstring of ``sampledjoin``."""
