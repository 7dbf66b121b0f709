"""Part of pathload."""
