"""Metadata of tensors and the state of a decomposition."""
