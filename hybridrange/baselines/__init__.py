"""The methods that the window stack is compared with, by descriptive names."""
