"""What a user asks for, and how it is to be computed."""
