"""Shared-folder tables, size checks and plan choice."""
