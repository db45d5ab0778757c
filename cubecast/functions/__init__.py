"""cubecast.functions"""
