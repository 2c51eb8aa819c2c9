"""Training-data operators; nothing else in trilist imports this subpackage."""
