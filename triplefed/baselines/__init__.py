"""What the adaptive engine is compared with."""
