"""The methods on streams."""
