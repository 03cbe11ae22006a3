"""Part of orderproof."""
