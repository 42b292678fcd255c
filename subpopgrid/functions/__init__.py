"""subpopgrid subpackage."""
