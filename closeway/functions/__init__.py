"""Package of closeway."""
