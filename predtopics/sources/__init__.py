"""Tables and fact files in and out."""
