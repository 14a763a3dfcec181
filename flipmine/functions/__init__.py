"""Part of flipmine."""
