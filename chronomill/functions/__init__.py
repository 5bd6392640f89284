"""Part of chronomill."""
