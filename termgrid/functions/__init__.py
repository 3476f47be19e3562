"""Column functions on texts and masks."""
