"""Event streams as growing tensors."""
