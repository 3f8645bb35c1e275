"""Training-data operators. Nothing else in ``sampledjoin`` imports this subpackage."""
