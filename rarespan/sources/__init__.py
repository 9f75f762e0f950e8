"""Series builders, readers, writers and generators."""
