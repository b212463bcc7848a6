"""canopy: grammar-based compression of forests stored as DataFrame rows."""
