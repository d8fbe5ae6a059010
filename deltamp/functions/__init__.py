"""Part of deltamp."""
