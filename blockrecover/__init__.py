"""Block recovery (file carving) as DataFrame plans."""
