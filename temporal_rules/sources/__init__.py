"""Sources, adapters to temporal relations, and sinks."""
