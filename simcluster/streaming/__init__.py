"""The search's operators on streams."""
