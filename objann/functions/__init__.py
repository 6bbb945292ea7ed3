"""Part of the object search library."""
