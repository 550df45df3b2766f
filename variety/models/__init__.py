"""Model families behind one registry."""
