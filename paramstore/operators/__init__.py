"""Analysis and compression operators over the relations of sources.zoo."""
