"""Block bitmaps of 512 bits."""
