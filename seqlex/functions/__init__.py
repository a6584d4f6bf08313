"""Column functions over sequences and confusion counts."""
