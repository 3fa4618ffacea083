"""Part of chaincores."""
