"""depscope subpackage."""
