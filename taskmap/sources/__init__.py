"""Graph builders over the given tables, files, sinks and generators."""
