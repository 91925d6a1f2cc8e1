"""Link streams."""
