"""Points and graphs from tables, text files and generators."""
