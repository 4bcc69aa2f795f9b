"""Methods over traces, masses and maps."""
