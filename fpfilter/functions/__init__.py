"""Hash functions and word-parallel slot tests."""
