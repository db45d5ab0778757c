"""cubecast.streaming"""
