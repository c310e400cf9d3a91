"""Center-based clustering that tolerates outliers, on any metric and at any scale."""
