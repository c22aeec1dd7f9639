"""Online insertion and membership on streams."""
