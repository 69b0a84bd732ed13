"""spreadlab subpackage."""
