"""Sources, sinks and stored layouts."""
