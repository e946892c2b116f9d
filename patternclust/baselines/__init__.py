"""The methods that the main one is compared with."""
