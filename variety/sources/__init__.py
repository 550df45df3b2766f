"""Reading and writing tables with explicit schemas."""
