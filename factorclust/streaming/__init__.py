"""What surrounds the method on streams."""
