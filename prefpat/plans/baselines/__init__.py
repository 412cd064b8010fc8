"""What the preference loop is compared with."""
