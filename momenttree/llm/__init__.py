"""Training-data operators: tokenising, filtering, de-duplication, scanning.

Nothing outside this subpackage imports it; it imports nothing from its siblings.
"""
