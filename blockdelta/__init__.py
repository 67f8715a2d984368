"""Hash-based differential checkpointing of large tabular and array state, as Spark plans."""
