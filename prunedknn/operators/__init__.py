"""Building, searching, joining and measuring."""
