"""Session settings, lineage and plan inspection."""
