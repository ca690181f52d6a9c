"""The commit and claim feed as streams."""
