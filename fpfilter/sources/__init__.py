"""Key sources and the persisted filter table."""
