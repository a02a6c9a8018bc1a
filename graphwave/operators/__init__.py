"""Graph layout, directories, exchanges, products and searches."""
