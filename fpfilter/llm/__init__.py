"""Training-data operators built beside the filter engine.

Nothing else in the package imports this subpackage; it can be deleted whole.
"""
