"""Source text to code-model rows."""
