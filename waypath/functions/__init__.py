"""Part of waypath."""
